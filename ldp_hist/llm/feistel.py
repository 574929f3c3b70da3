"""Training-order materialisation: a keyed permutation of token sequences, written as fixed-stride shards."""

from __future__ import annotations

import base64
import functools
import glob
import os
import re
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import tiktoken
import zstandard
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ldp_hist.llm.shared import materialise, shared_dir
from ldp_hist.llm.words import mix

#: A vocabulary of ranked byte strings, and the pattern that cuts texts before merging (both public; see its folder).
DEFAULT_RANKS = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: END closes a document and PAD fills its last sequence; both ids are free in the vocabulary, and all fit 16 bits.
END, PAD = 50256, 50257
SEQUENCE, SHARD_SEQUENCES, ROUNDS = 512, 16_384, 6
#: Characters that are tokenised at a time (twice as many where no space comes).
PORTION = 1 << 16
#: Sequences that a task holds before it sends them off, grouped by shard, and the most tasks that write shards.
HELD, WRITERS = 32_768, 20_000


def read_ranks(path: str = DEFAULT_RANKS) -> dict[bytes, int]:
    """Reads the vocabulary on the driver; executors get it with the task, so the file need not be where they are."""
    with open(path, "rb") as f:
        return {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, f)}


_BEFORE_WORD = re.compile(r" (?=\S)")


def portions(text: str, size: int = PORTION) -> list[str]:
    """``text`` in order, cut before the first space that a word follows after every ``size`` characters, and in twice that run without one.

    The pattern has a boundary before such a space in any case, so cutting there changes no id.
    """
    out, at = [], 0
    while len(text) - at > size:
        found = _BEFORE_WORD.search(text, at + size, at + 2 * size)
        end = found.start() if found else at + 2 * size
        out.append(text[at:end])
        at = end
    return [*out, text[at:]]


#: Bytes of text whose words are told apart at a time, and that are cut at a time; the different words that a worker keeps at most (some 10 MB); bytes of a word that is told apart as a number.
SLICE, PART, KEPT, SHORT = 1 << 22, 1 << 18, 1 << 18, 7


def _kind(byte: int) -> int:
    """Bits: a space or line end, the first of a character that is surely not white (those beyond ASCII that are begin with C2, E1, E2 or E3),
    an ASCII letter or digit, other ASCII that is seen."""
    seen = 0x21 <= byte <= 0x7E
    solid = seen or (byte >= 0xC3 and byte not in (0xE1, 0xE2, 0xE3))
    return (byte in b" \n") | solid << 1 | (seen and chr(byte).isalnum()) << 2 | (seen and not chr(byte).isalnum()) << 3


KINDS = bytes(map(_kind, range(256)))
#: Words that a line end after them keeps apart from the next: not white but for one space in front.
_PLAIN = r"^ ?[^\s\x0b\x1c-\x1f\x{85}\p{Z}]+\z"


class Words:
    """Different words, and the ids of each as bytes."""

    def __init__(self, words: pa.Array, ids: pa.Array):
        self.words, self.ids = words, ids


class Tokens:
    """Texts to 16-bit ids.

    The pattern has a boundary before the last of the white characters that come before one that is not white, on both sides of that one if it is a line
    end, and behind the last of a row of letters or numbers; it never looks back across a boundary. Texts are cut at such places, read off their bytes, and each
    different word is tokenised once and kept. When they become too many, those stay that the last texts have more than once. Texts with a word longer
    than ``PORTION`` bytes are taken in ``portions``.
    """

    def __init__(self, ranks):
        from public_tokenizers import PATTERN

        self.encoding = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=dict(ranks), special_tokens={})
        (self.line_end,) = self.encoding.encode_ordinary("\n")
        self.kept = Words(pa.array([], pa.string()), pa.array([], pa.binary()))

    def number(self, text: str) -> int:
        """How many ids the whole text has, END included."""
        return self.numbers(pa.array([text]))[0]

    def ids(self, text: str) -> np.ndarray:
        """The ids of the whole text and END."""
        return next(self.all_ids(pa.array([text])))

    def numbers(self, texts: pa.Array) -> list[int]:
        """``number`` of each text."""
        return [n + 1 for some in _slices(texts) for n in self._numbers(some)]

    def all_ids(self, texts: pa.Array):
        """``ids`` of each text, one after the other."""
        end = np.array([END], "<u2")
        for some in _slices(texts):
            for ids in self._all_ids(some):
                yield np.concatenate([*ids, end])

    def _numbers(self, texts: pa.Array) -> list[int]:
        if _long(texts):
            return [sum(self._numbers(pa.array([p]))[0] for p in portions(texts[0].as_py(), SLICE))]
        whole, first, at, words = self._cut(texts)
        upto = np.concatenate([[0], np.cumsum(pc.binary_length(words.ids).to_numpy()[at] // 2, dtype=np.int64)])
        out = np.diff(upto[first])
        for i in whole:
            out[i] = sum(len(self.encoding.encode_ordinary(p)) for p in portions(texts[i].as_py()))
        return out.tolist()

    def _all_ids(self, texts: pa.Array):
        """The ids of each text, in some arrays."""
        if _long(texts):
            yield [ids for p in portions(texts[0].as_py(), SLICE) for some in self._all_ids(pa.array([p])) for ids in some]
            return
        whole, first, at, words = self._cut(texts)
        ids = words.ids.take(pa.array(at))
        upto = np.frombuffer(ids.buffers()[1], np.int32)[first] // 2 if len(ids) else first
        ids = np.frombuffer(ids.buffers()[2], "<u2") if len(ids) else np.zeros(0, "<u2")
        for i in range(len(texts)):
            if i in whole:
                yield [np.array(self.encoding.encode_ordinary(p), "<u2") for p in portions(texts[i].as_py())]
            else:
                yield [ids[upto[i] : upto[i + 1]]]

    def _cut(self, texts: pa.Array):
        """Texts that are taken in portions; of all others where the words of each begin, the place of each word among the different ones, and these."""
        _, offsets, data = texts.buffers()
        offsets = np.frombuffer(offsets, np.int32)[texts.offset : texts.offset + len(texts) + 1]
        data = np.frombuffer(data or b"", np.uint8)[offsets[0] : offsets[-1]]
        offsets = offsets - offsets[0]
        begins = np.concatenate([*_begins(data, offsets), [len(data)]]).astype(np.int32)
        long = np.diff(begins) > PORTION
        if long.any():
            whole = np.unique(np.searchsorted(offsets, begins[:-1][long], "right") - 1)
            others = np.ones(len(texts), bool)
            others[whole] = False
            return set(whole.tolist()), *self._cut(pc.if_else(pa.array(others), texts, ""))[1:]
        words = pa.StringArray.from_buffers(len(begins) - 1, pa.py_buffer(begins), pa.py_buffer(data))
        return set(), np.searchsorted(begins, offsets), *self._known(words)

    def _known(self, words: pa.Array) -> tuple[np.ndarray, Words]:
        """The place of each of the ``words`` among different ones, and these."""
        short = pc.binary_length(words).to_numpy() <= SHORT
        numbered = pa.array(_as_numbers(words, short)).dictionary_encode()
        few, n = _as_words(numbered.dictionary.to_numpy()), len(self.kept.words)
        coded = pa.concat_arrays([self.kept.words, few, words.filter(pa.array(~short))]).dictionary_encode()
        out = self.kept = Words(coded.dictionary, pa.concat_arrays([self.kept.ids, self._made(coded.dictionary.slice(n))]))
        places, at = coded.indices.to_numpy()[n:], np.empty(len(words), np.int32)
        at[short] = places[: len(few)][numbered.indices.to_numpy()]
        at[~short] = places[len(few) :]
        if len(out.words) > KEPT:
            often = np.flatnonzero(np.bincount(at, minlength=len(out.words)) > 1)
            often = pa.array(often[: KEPT // 2])
            self.kept = Words(out.words.take(often), out.ids.take(often))
        return at, out

    def _made(self, words: pa.Array) -> pa.Array:
        """The ids of ``words``. Line ends keep those apart that are plain; the others are tokenised one by one."""
        plain = pc.match_substring_regex(words, _PLAIN)
        some, flat, upto = words.filter(plain), [], [np.zeros(1, np.int64)]
        for a in range(0, len(some), 1 << 15):
            part = some.slice(a, 1 << 15)
            line = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(part)], pa.int32()), part), "\n")[0].as_py()
            ids = np.array(self.encoding.encode_ordinary(line + "\n"), "<u2")
            marks = np.flatnonzero(ids == self.line_end)
            if len(marks) != len(part):
                raise ValueError(f"{len(part)} words have {len(marks)} ends")
            flat.append(ids[ids != self.line_end])
            upto.append(upto[-1][-1] + marks - np.arange(len(marks)))
        offsets, flat = 2 * np.concatenate(upto).astype(np.int32), np.concatenate([np.zeros(0, "<u2"), *flat])
        made = pa.Array.from_buffers(pa.binary(), len(some), [None, pa.py_buffer(offsets), pa.py_buffer(flat)])
        if len(some) == len(words):
            return made
        plain = plain.to_numpy(zero_copy_only=False)
        odd = pa.array([np.array(self.encoding.encode_ordinary(w), "<u2").tobytes() for w in words.filter(pa.array(~plain)).to_pylist()], pa.binary())
        order = np.argsort(np.concatenate([np.flatnonzero(plain), np.flatnonzero(~plain)]))
        return pa.concat_arrays([made, odd]).take(pa.array(order))


def _as_numbers(words: pa.Array, short: np.ndarray) -> np.ndarray:
    """Those of the words, which lie one after the other, that are ``short``: their bytes, ``SHORT`` at most, and how many these are."""
    _, offsets, data = words.buffers()
    offsets, data, out = np.frombuffer(offsets, np.int32), np.frombuffer(data or b"", np.uint8), [np.zeros(0, "<u8")]
    mask = (np.uint64(1) << (np.arange(SHORT + 1, dtype=np.uint64) * np.uint64(8))) - np.uint64(1)
    for a in range(0, len(words), PART // 4):
        own = offsets[a : min(a + PART // 4, len(words)) + 1]
        eight = np.ndarray(own[-1] - own[0] + 1, "<u8", np.append(data[own[0] : own[-1]], np.zeros(8, np.uint8)), 0, (1,))
        some = short[a : a + len(own) - 1]
        sizes = np.diff(own)[some].astype(np.uint64)
        out.append(eight[own[:-1][some] - own[0]] & mask[sizes] | sizes << np.uint64(8 * SHORT))
    return np.concatenate(out)


def _as_words(numbers: np.ndarray) -> pa.Array:
    """The words of ``_as_numbers``."""
    table = numbers.astype("<u8").view(np.uint8).reshape(-1, 8)
    offsets = np.concatenate([[0], np.cumsum(table[:, SHORT], dtype=np.int64)]).astype(np.int32)
    return pa.StringArray.from_buffers(len(numbers), pa.py_buffer(offsets), pa.py_buffer(table[:, :SHORT][np.arange(SHORT) < table[:, SHORT:]]))


def _begins(data: np.ndarray, offsets: np.ndarray):
    """Where the words of texts begin that lie one after the other, some texts at a time, so that these stay in the processor's cache."""
    at = 0
    while at < len(offsets) - 1:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + PART, "right")) - 1)
        a, b = offsets[at], offsets[end]
        yield np.flatnonzero(_boundaries(data[a:b], offsets[at : end + 1] - a)) + a
        at = end


def _boundaries(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Whether a word begins at each byte of texts that lie one after the other."""
    kinds, out = np.frombuffer(data.tobytes().translate(KINDS), np.uint8), np.zeros(len(data), np.uint8)
    starts = offsets[:-1][np.diff(offsets) > 0]
    spaces = kinds[:-1] & kinds[1:] >> 1 & 1
    spaces[starts[1:] - 1] = 0  # what follows is another text
    out[:-1] = spaces
    out[1:] |= spaces & (data[:-1] == 0x0A)
    out[1:] |= kinds[:-1] >> 2 & kinds[1:] >> 3 & 1
    # The letters from U+00C0 to U+00FF.
    out[2:] |= kinds[2:] >> 3 & (data[:-2] == 0xC3) & (data[1:-1] != 0x97) & (data[1:-1] != 0xB7)
    out[starts] = 1
    return out.view(bool)


def _long(texts: pa.Array) -> bool:
    """Whether that is one text so long that it is cut into slices itself, whose characters have four bytes at most."""
    return len(texts) == 1 and pc.binary_length(texts)[0].as_py() > 8 * SLICE


def _slices(texts: pa.Array):
    """``texts`` in slices of about ``SLICE`` bytes, a text at least."""
    upto = np.cumsum(pc.binary_length(texts).to_numpy(), dtype=np.int64)
    at = 0
    while at < len(texts):
        end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + SLICE, "right")))
        yield texts.slice(at, end - at)
        at = end
        pa.default_memory_pool().release_unused()


@functools.lru_cache(maxsize=2)
def _tokens(ranks: tuple) -> Tokens:
    """A worker's own, kept from task to task."""
    return Tokens(ranks)


def permute(index: np.ndarray, n: int, key: int, rounds: int = ROUNDS) -> np.ndarray:
    """The slots of sequence numbers 0..n-1 under a balanced Feistel network that walks its cycles.

    The network permutes the least 2**(2w) >= n; a value that lands outside 0..n-1 goes through it again
    until it falls inside, which keeps the map a permutation of 0..n-1 (under four passes on average).
    """
    half = max(1, -(-max(n - 1, 1).bit_length() // 2))
    mask, shift = np.uint64((1 << half) - 1), np.uint64(half)
    keys = mix(np.arange(1, rounds + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(key % (1 << 64)))
    out = index.astype(np.uint64)
    walking = np.arange(len(out))
    while len(walking):
        left, right = out[walking] >> shift, out[walking] & mask
        for k in keys:
            left, right = right, left ^ (mix(right + k) & mask)
        out[walking] = (left << shift) | right
        walking = walking[out[walking] >= n]
    return out.astype(np.int64)


def _placed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(file, block, doc_id, text): where each row is stored; rows that no file holds are written to one first."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))

    def stored(df: DataFrame) -> DataFrame:
        return df.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), "doc_id", "text")

    try:
        return stored(rows)
    except AnalysisException:
        return stored(materialise(rows))


def _counts(ranks, sequence: int):
    """(file, block, n): how many sequences the documents of a file split have, a row for each batch."""

    def run(batches):
        tokens = _tokens(ranks.value)
        for batch in batches:
            found: dict[tuple, int] = {}
            for file, block, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), tokens.numbers(batch.column(2)), strict=True):
                found[file, block] = found.get((file, block), 0) - (-n // sequence)
            yield pa.record_batch([pa.array([f for f, _ in found], pa.string()), pa.array([b for _, b in found], pa.int64()), pa.array(list(found.values()), pa.int64())], names=["file", "block", "n"])

    return run


#: A sequence on its way to its shard; its ids follow those of the ones before it.
SENT = np.dtype([("slot", "<i8"), ("doc_id", "<i8"), ("known", "<i8"), ("seq_no", "<i8"), ("n_tokens", "<i8")])


def _blocks(ranks, sequence: int, shard_sequences: int, total: int, key: int):
    """(shard, block): the sequences that a task has for a shard, packed together. Rows come in the order of their file split, with its ``start``."""

    def packed(heads: list[tuple], ids: list[np.ndarray]):
        rows = np.array(heads, SENT)
        rows["slot"] = permute(rows["slot"], total, key)
        shard = rows["slot"] // shard_sequences
        order = np.argsort(shard, kind="stable")
        cuts = np.flatnonzero(np.diff(shard[order])) + 1
        groups = np.split(order, cuts)
        shrink = zstandard.ZstdCompressor(level=1).compress
        blocks = [shrink(len(g).to_bytes(8, "little") + rows[g].tobytes() + b"".join([ids[i].tobytes() for i in g.tolist()])) for g in groups]
        return pa.record_batch([pa.array(shard[[g[0] for g in groups]]), pa.array(blocks, pa.binary())], names=["shard", "block"])

    def run(batches):
        tokens = _tokens(ranks.value)
        at, nth, heads, held = None, 0, [], []
        for batch in batches:
            rows = zip(*(batch.column(c).to_pylist() for c in (0, 1, 2, 4)), tokens.all_ids(batch.column(3)), strict=True)
            for file, block, doc_id, start, ids in rows:
                if (file, block) != at:
                    at, nth = (file, block), start
                for seq_no, a in enumerate(range(0, len(ids), sequence)):
                    own = ids[a : a + sequence]
                    heads.append((nth, doc_id or 0, doc_id is not None, seq_no, len(own)))
                    held.append(own)
                    nth += 1
                if len(heads) >= HELD:
                    yield packed(heads, held)
                    heads, held = [], []
        if heads:
            yield packed(heads, held)

    return run


#: What a shard file holds after its records: an index entry for each, then their number and a line end.
ENTRY = np.dtype([("doc_id", "<i8"), ("known", "<i8"), ("seq_no", "<i8"), ("n_tokens", "<i8")])
FOOTER = 8 + 1


def _shard_bytes(sequence: int):
    """(shard, bytes) of blocks that come by shard: records in the order of their slots, index, number of records."""

    def whole(shard: int, blocks: list[bytes]) -> pa.RecordBatch:
        heads, ids = [], []
        for block in blocks:
            n = int.from_bytes(block[:8], "little")
            heads.append(np.frombuffer(block, SENT, n, 8))
            ids.append(np.frombuffer(block, "<u2", offset=8 + n * SENT.itemsize))
        rows, flat = np.concatenate(heads), np.concatenate(ids)
        ends = np.cumsum(rows["n_tokens"])
        table = np.full((len(rows), sequence), PAD, "<u2")
        order = np.argsort(rows["slot"])
        for place, i in enumerate(order.tolist()):
            n = rows["n_tokens"][i]
            table[place, :n] = flat[ends[i] - n : ends[i]]
        index = np.zeros(len(rows), ENTRY)
        for name in ENTRY.names:
            index[name] = rows[name][order]
        data = b"".join([table.tobytes(), index.tobytes(), len(rows).to_bytes(8, "little")])
        return pa.record_batch([pa.array([shard], pa.int64()), pa.array([data], pa.binary())], names=["shard", "bytes"])

    def run(batches):
        grow = zstandard.ZstdDecompressor().decompress
        at, held = None, []
        for batch in batches:
            for shard, block in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if shard != at and held:
                    yield whole(at, held)
                    held = []
                at = shard
                held.append(grow(block.as_py()))
        if held:
            yield whole(at, held)

    return run


def shard_files(
    docs: DataFrame, key: int = 20240229, sequence: int = SEQUENCE, shard_sequences: int = SHARD_SEQUENCES,
    id_col: str = "doc_id", text_col: str = "text", ranks_path: str = DEFAULT_RANKS,
) -> DataFrame:
    """(shard, bytes): the training order of ``docs`` as the contents of its shard files.

    A document's token ids and ``END`` are cut into sequences of ``sequence``; the last one is padded. Sequences are
    numbered without a gap in the order in which the table stores its documents: by file, place in the file and place in the
    document. A key and a table thus fix the order, however its files are split among tasks. A first pass counts the
    sequences of each file split, whose running sum (a row a split) is all that is broadcast; the second one makes them. The keyed
    permutation gives each number its slot, ``shard_sequences`` to a shard. A task sends a shard all it has for it as one compressed
    block, by a range of shards, and the tasks of the ranges write whole shards: the ids are shuffled once, and nothing else is stored.

    Null texts count as empty (one sequence, just ``END``); null ids are allowed and repeated rows get slots of
    their own. Empty tables give empty results; other columns are ignored. Texts may have any length.
    """
    ranks = docs.sparkSession.sparkContext.broadcast(tuple(read_ranks(ranks_path).items()))
    rows = _placed(docs, id_col, text_col)
    counts = rows.select("file", "block", "text").mapInArrow(_counts(ranks, sequence), "file string, block long, n long")
    counts = materialise(counts.groupBy("file", "block").agg(F.sum("n").alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    earlier = Window.orderBy("file", "block").rowsBetween(Window.unboundedPreceding, -1)
    starts = F.broadcast(counts.select("file", "block", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("start")))
    numbered = rows.join(starts, ["file", "block"]).select("file", "block", "doc_id", "text", "start")
    blocks = numbered.mapInArrow(_blocks(ranks, sequence, shard_sequences, total, key), "shard long, block binary")
    shards = max(1, -(-total // shard_sequences))
    ranges = min(shards, WRITERS)
    dealt = blocks.repartitionById(ranges, F.floor(F.col("shard") * ranges / shards).cast("int"))
    return dealt.sortWithinPartitions("shard").mapInArrow(_shard_bytes(sequence), "shard long, bytes binary")


ROWS = "slot long, doc_id long, seq_no long, shard long, n_tokens int, record_crc32 long, record binary, shard_offset long"


def training_order(docs: DataFrame, **how) -> DataFrame:
    """Every sequence of ``docs`` in training order without writing shards: the rows that ``shard_files`` would hold.

    ``shard_offset`` is a record's byte offset in its shard, always a multiple of 2*sequence.
    """
    sizes = how.get("sequence", SEQUENCE), how.get("shard_sequences", SHARD_SEQUENCES)
    as_written = shard_files(docs, **how).select("shard", F.concat("bytes", F.lit(b"\n")).alias("content"))  # the writer ends its line
    return as_written.mapInArrow(_shard_rows(*sizes), ROWS)


def _shard_rows(sequence: int, shard_sequences: int):
    """The rows of shard files: all values, the checksums included, come from the bytes that were written."""

    def run(batches):
        for batch in batches:
            for shard, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                data = content.as_buffer()
                view, stride = memoryview(data), 2 * sequence
                n = int.from_bytes(view[len(view) - FOOTER : len(view) - 1], "little")
                if len(view) != n * (stride + ENTRY.itemsize) + FOOTER:
                    raise ValueError(f"shard {shard} has {len(view)} bytes for {n} records")
                index = np.frombuffer(view[n * stride : n * stride + n * ENTRY.itemsize], ENTRY)
                for a in range(0, n, 1024):
                    some = index[a : a + 1024]
                    records = [bytes(view[i * stride : (i + 1) * stride]) for i in range(a, a + len(some))]
                    at = np.arange(a, a + len(some), dtype=np.int64)
                    yield pa.record_batch(
                        [pa.array(shard * shard_sequences + at), pa.array(some["doc_id"].copy(), mask=some["known"] == 0), pa.array(some["seq_no"].copy()), pa.array(np.full(len(some), shard, np.int64)),
                         pa.array(some["n_tokens"].astype(np.int32)), pa.array([zlib.crc32(r) for r in records], pa.int64()), pa.array(records, pa.binary()), pa.array(at * stride)],
                        names=["slot", "doc_id", "seq_no", "shard", "n_tokens", "record_crc32", "record", "shard_offset"],
                    )

    return run


def write_shards(files: DataFrame, folder: str) -> None:
    """Writes ``shards/shard=N/`` with one file each below ``folder``, a Hadoop path, from (shard, bytes).

    Record i of a shard starts at byte 2*sequence*i of its file; the index of ids comes after the records. Shards are written
    by the tasks that made them. Spark's committer keeps one attempt of a retried task, and a reader never sees half a shard.
    """
    files.select("shard", F.col("bytes").cast("string").alias("value")).write.mode("overwrite").partitionBy("shard").option("compression", "none").text(f"{folder}/shards")


def written_sequences(spark: SparkSession, folder: str, sequence: int = SEQUENCE, shard_sequences: int = SHARD_SEQUENCES) -> DataFrame:
    """The rows of ``training_order``, read from the shard files below ``folder``."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/shards")
    if not any("shard=" in str(x.getPath()) for x in path.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(path)):
        return spark.createDataFrame([], ROWS)
    shard = F.regexp_extract("path", "/shard=([0-9]+)/", 1).cast("long").alias("shard")
    files = spark.read.format("binaryFile").load(f"{folder}/shards/shard=*/part-*").select(shard, "content")
    return files.mapInArrow(_shard_rows(sequence, shard_sequences), ROWS)


def training_shards(docs: DataFrame, folder: str | None = None, **how) -> DataFrame:
    """Writes the training order of ``docs`` as shards (by default to a new folder in the shared one) and returns the rows they hold.

    The shard files stay for the readers; rows are read from them, not from what they were made of.
    """
    folder = folder or f"{shared_dir(docs.sparkSession)}/training-order-{uuid.uuid4().hex}"
    write_shards(shard_files(docs, **how), folder)
    return written_sequences(docs.sparkSession, folder, **{k: v for k, v in how.items() if k in ("sequence", "shard_sequences")})


def read_sequences(folder: str, start: int, count: int, sequence: int = SEQUENCE, shard_sequences: int = SHARD_SEQUENCES) -> np.ndarray:
    """``count`` records from global slot ``start`` on, by seeking in a mounted folder: how a reader resumes."""
    out = []
    while count > 0:
        shard, at = divmod(start, shard_sequences)
        found = glob.glob(os.path.join(glob.escape(folder), "shards", f"shard={shard}", "part-*"))
        if not found:
            break
        with open(found[0], "rb") as f:
            f.seek(-FOOTER, os.SEEK_END)
            n = min(count, max(0, int.from_bytes(f.read(8), "little") - at))
            f.seek(at * 2 * sequence)
            got = np.frombuffer(f.read(n * 2 * sequence), "<u2").reshape(-1, sequence)
        if not len(got):
            break
        out.append(got)
        start, count = start + len(got), count - len(got)
    return np.concatenate(out) if out else np.zeros((0, sequence), "<u2")

"""SentencePiece encoding and decoding by a streaming Viterbi search over the vocabulary's piece scores."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: An unknown character costs this much more than the least likely piece.
UNKNOWN_PENALTY = 10.0
#: Portions remembered by each worker (as many again from the time before), and the longest that are.
MEMO, MEMO_CHARS = 300_000, 64


_WARM: dict = {}


@dataclass
class Vocabulary:
    """Pieces with their scores and ids, byte pieces for the rest, and the longest piece's length."""

    pieces: list[str]
    scores: dict[str, float]
    ids: dict[str, int]
    byte_ids: list[int]
    unknown: int
    longest: int
    unknown_score: float
    splits: bool
    trie: dict | None = None
    raw: list[bytes] | None = None
    memo: dict[str, bytes] = field(default_factory=dict)
    older: dict[str, bytes] = field(default_factory=dict)

    def __getstate__(self):
        return self.__dict__ | {"trie": None, "raw": None, "memo": {}, "older": {}}

    def warm(self) -> Vocabulary:
        """This worker's own copy, which keeps its trie and its memo from task to task."""
        key = (len(self.pieces), self.longest, hash(tuple(self.scores.items())))
        return _WARM.setdefault(key, self)

    def root(self) -> dict:
        """Children by character; under the empty string the score of the piece that ends here."""
        if self.trie is None:
            self.trie = {}
            for piece, score in self.scores.items():
                node = self.trie
                for c in piece:
                    node = node.setdefault(c, {})
                node[""] = score
        return self.trie

    def bytes_of(self) -> list[bytes]:
        """What each id stands for in UTF-8, a space for the space mark."""
        if self.raw is None:
            self.raw = [p.replace(SPACE, " ").encode("utf-8", "surrogatepass") for p in self.pieces]
            for b, i in enumerate(self.byte_ids):
                self.raw[i] = bytes([b])
        return self.raw

    @classmethod
    def load(cls, path: str = DEFAULT_MODEL) -> Vocabulary:
        """Reads a model file on the driver; what executors need travels with the task (under 2 MB)."""
        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        every = range(sp.get_piece_size())
        pieces = [sp.id_to_piece(i) for i in every]
        plain = [i for i in every if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        # A model may mark runs of spaces with a sentinel score; the scale of the others bounds it.
        real = [sp.get_score(i) for i in plain if sp.get_score(i) > -1e8]
        floor = min(real, default=0.0)
        scores = {pieces[i]: max(sp.get_score(i), floor) for i in plain}
        return cls(
            pieces, scores, {pieces[i]: i for i in plain}, [i for i in every if sp.is_byte(i)], sp.unk_id(),
            max(map(len, scores), default=1), floor - UNKNOWN_PENALTY, not any(re.search(f"[^{SPACE}]{SPACE}", p) for p in scores),
        )


class StreamingViterbi:
    """Best segmentation of a stream of characters, with a window of characters that grows with the longest piece only.

    ``feed`` takes characters in any portions and returns the ids that are settled. From every boundary in turn the
    pieces that begin there reach out, down the trie, by ``longest`` characters at most, so only the boundaries in that
    reach have paths that can still win. Every ``longest`` boundaries the backpointer paths of these are followed; where
    all of them have come together in one boundary, what lies before it is committed and forgotten.
    """

    def __init__(self, vocabulary: Vocabulary):
        self.v, self.root = vocabulary, vocabulary.root()
        self.text, self.at, self.due = "", 0, vocabulary.longest
        self.score, self.back = [0.0], [0]

    def feed(self, more: str, last: bool = False) -> list[int]:
        """Ids settled by now; ``last`` says that no character follows, which settles all."""
        out: list[int] = []
        self.text += more
        while True:
            # A boundary is done when all characters that its pieces could have are there.
            stop = len(self.text) if last else len(self.text) - self.v.longest + 1
            self._search(min(stop, self.due))
            if self.at < self.due or self.at >= stop:
                break
            out += self._commit()
            self.due = self.at + self.v.longest
        if last:
            out += self._ids(len(self.text))
            self.text, self.at, self.due, self.score, self.back = "", 0, self.v.longest, [0.0], [0]
        return out

    def finish(self) -> list[int]:
        return self.feed("", last=True)

    def _search(self, stop: int) -> None:
        text, score, back, root, unknown = self.text, self.score, self.back, self.root, self.v.unknown_score
        room = len(text) + 1 - len(score)
        if room > 0:
            score += [-1e300] * room
            back += [0] * room
        for s in range(self.at, stop):
            here, node, e = score[s], root, s
            if here + unknown > score[s + 1]:
                score[s + 1], back[s + 1] = here + unknown, s
            for c in text[s : s + self.v.longest]:
                node = node.get(c)
                if node is None:
                    break
                e += 1
                own = node.get("")
                if own is not None and here + own > score[e]:
                    score[e], back[e] = here + own, s
        self.at = max(self.at, stop)

    def _commit(self) -> list[int]:
        """The ids before the boundary in which all surviving paths come together; none if that is the first one."""
        alive = {b for b in range(self.at, min(len(self.text), self.at + self.v.longest) + 1) if self.score[b] > -1e299}
        while len(alive) > 1:
            last = max(alive)
            alive.discard(last)
            alive.add(self.back[last])
        boundary = alive.pop()
        if not boundary:
            return []
        out, base = self._ids(boundary), self.score[boundary]
        self.text, self.at = self.text[boundary:], self.at - boundary
        self.score = [s - base if s > -1e299 else s for s in self.score[boundary:]]
        self.back = [max(0, b - boundary) for b in self.back[boundary:]]
        return out

    def _ids(self, end: int) -> list[int]:
        cuts = []
        while end:
            cuts.append((self.back[end], end))
            end = self.back[end]
        out = []
        for s, e in reversed(cuts):
            piece = self.text[s:e]
            known = self.v.ids.get(piece)
            if known is not None:
                out.append(known)
            elif self.v.byte_ids:
                out += [self.v.byte_ids[b] for b in piece.encode("utf-8", "surrogatepass")]
            else:
                out.append(self.v.unknown)
        return out


_PORTIONS = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")


def encode(v: Vocabulary, text: str | None) -> np.ndarray:
    """Ids of the whole text; the empty text and null have none.

    A space is put in front, spaces become the space mark, and the stream is fed in portions that begin at a mark.
    Where no piece holds a mark after another character, all paths meet before a mark, so the stream is empty
    there: what it says to the next portion depends on that alone, and is remembered.
    """
    if not text:
        return np.zeros(0, np.int32)
    stream, portions = StreamingViterbi(v), _PORTIONS.findall(SPACE + text.replace(" ", SPACE))
    if not v.splits:
        ids = [i for p in portions for i in stream.feed(p)]
        return np.array(ids + stream.finish(), np.int32)

    def fresh(portion: str) -> bytes:
        known = v.older.get(portion)
        if known is None:
            known = np.array(stream.feed(portion, last=True), np.int32).tobytes()
        if len(portion) <= MEMO_CHARS:
            if len(v.memo) >= MEMO:
                v.older, v.memo = v.memo, {}
            v.memo[portion] = known
        return known

    return np.frombuffer(b"".join([v.memo.get(p) or fresh(p) for p in portions]), np.int32)


def decode(v: Vocabulary, ids: np.ndarray) -> str:
    """The text of the ids: pieces joined, byte pieces as UTF-8, space marks as spaces, the first one gone.

    An id that the vocabulary lacks, negative ones too, stands for the replacement character.
    """
    raw = v.bytes_of()
    if len(ids) and (ids.min() < 0 or ids.max() >= len(raw)):
        parts = [raw[i] if 0 <= i < len(raw) else "\ufffd".encode() for i in ids.tolist()]
    else:
        parts = map(raw.__getitem__, ids.tolist())
    text = b"".join(parts).decode("utf-8", "replace")
    return text[1:] if text.startswith(" ") else text


def _encode(vocabulary: Vocabulary, carried: int):
    def run(batches):
        v = vocabulary.warm()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = part.column(carried).to_pylist()
                ids = [encode(v, t) for t in texts]
                exact = [decode(v, i) == (t or "") for i, t in zip(ids, texts, strict=True)]
                ends = np.cumsum([0, *map(len, ids)], dtype=np.int32)
                flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
                yield pa.record_batch(
                    [*part.columns[:carried], pa.array([len(i) for i in ids], pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, pa.int32())), pa.array(exact)],
                    names=[*part.schema.names[:carried], "n_tokens", "token_ids", "round_trip"],
                )

    return run


def encode_documents(docs: DataFrame, model: str = DEFAULT_MODEL, carry: list[str] | None = None) -> DataFrame:
    """``carry`` columns (doc_id) of every row with n_tokens, token_ids and round_trip, which replace carried ones of these names.

    ``round_trip`` is whether decoding gives the whole text back; it fails only for texts that hold the
    space mark itself or unpaired surrogates. Null and empty texts have no ids and round-trip to the empty text.
    Ties go to the segmentation whose last piece starts earlier. Empty tables give empty results.
    """
    carry = [c for c in carry or ["doc_id"] if c not in ("n_tokens", "token_ids", "round_trip")]
    kept = docs.select(*[F.col(f"`{c}`") for c in carry])
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields)
    read = docs.select(*[F.col(f"`{c}`") for c in carry], F.col("`text`").alias("__text"))
    return read.mapInArrow(_encode(Vocabulary.load(model), len(carry)), f"{schema}, n_tokens long, token_ids array<int>, round_trip boolean")


def _decode(v: Vocabulary):
    def run(batches):
        for batch in batches:
            texts = [decode(v, np.array(x or [], np.int32)) for x in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return run


def decode_documents(encoded: DataFrame, model: str = DEFAULT_MODEL) -> DataFrame:
    """doc_id and the text of its ``token_ids``; null ids and lists give the empty text, repeated rows repeated results."""
    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("token_ids").cast("array<int>")).mapInArrow(_decode(Vocabulary.load(model)), "doc_id long, text string")

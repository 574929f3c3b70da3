"""SimHash near-dedup with BK-trees.

Fingerprints are dealt to shards so that any two within the radius share a shard: by the bit blocks of a
multi-index (exact), or by MinHash bands of the shingle set where the radius is too wide for blocks. Every
shard holds the BK-tree of its distinct fingerprints; a tree is built and searched where its shard is,
because the fingerprints of a corpus have no size bound that would allow sending all trees everywhere.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldp_hist.llm.shared import connected_components, materialise, run_of
from ldp_hist.llm.words import majority_bits, mix, shingle_hashes, word_hashes

#: Fingerprints that a tree leaves undivided, those that a shard has on average, and at most before it is split.
LEAF, SHARD, SPLIT_ABOVE = 8, 256, 8192


class BKTree:
    """A Burkhard-Keller tree over an array of 64-bit fingerprints.

    A node is a pivot and its children, keyed by their integer Hamming distance to the pivot; up to
    ``LEAF`` fingerprints are left as one array. ``search`` follows, for a whole batch of queries, only
    the edges from distance-radius to distance+radius; ``followed`` and ``pruned`` count a query's edges.
    """

    def __init__(self, fingerprints: np.ndarray):
        self.values = fingerprints.astype(np.uint64)
        self.root = self._build(np.arange(len(fingerprints)))
        self.followed = self.pruned = 0

    def _build(self, members: np.ndarray):
        if len(members) <= LEAF:
            return members
        pivot, rest = members[0], members[1:]
        distance = np.bitwise_count(self.values[rest] ^ self.values[pivot])
        order = np.argsort(distance, kind="stable")
        keys, starts = np.unique(distance[order], return_index=True)
        if len(keys) == 1 and keys[0] == 0:
            return members
        parts = np.split(rest[order], starts[1:])
        return pivot, {int(k): self._build(part) for k, part in zip(keys, parts, strict=True)}

    def search(self, queries: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Batches of (query number, member number) for all pairs within ``radius``."""
        queries = queries.astype(np.uint64)
        stack = [(self.root, np.arange(len(queries)))]
        while stack:
            node, asked = stack.pop()
            if not len(asked):
                continue
            if isinstance(node, np.ndarray):
                for at in range(0, len(asked), 4096):
                    some = asked[at : at + 4096]
                    near = np.bitwise_count(queries[some][:, None] ^ self.values[node][None, :]) <= radius
                    q, m = np.nonzero(near)
                    yield some[q], node[m]
                continue
            pivot, children = node
            distance = np.bitwise_count(queries[asked] ^ self.values[pivot]).astype(np.int16)
            hit = asked[distance <= radius]
            yield hit, np.full(len(hit), pivot)
            for edge, child in children.items():
                near = asked[np.abs(distance - edge) <= radius]
                self.followed, self.pruned = self.followed + len(near), self.pruned + len(asked) - len(near)
                if len(near):
                    stack.append((child, near))


class Forest:
    """Union-find over numbers; ``union`` tells whether two trees became one."""

    def __init__(self, n: int):
        self.parent = list(range(n))

    def find(self, x: int) -> int:
        while self.parent[x] != x:
            self.parent[x] = self.parent[self.parent[x]]
            x = self.parent[x]
        return x

    def union(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a != b:
            self.parent[max(a, b)] = min(a, b)
        return a != b


def spanning_links(fingerprints: np.ndarray, radius: int, accept=None, asked=None, roots=None) -> list[tuple[int, int]]:
    """Links that connect what the radius (and ``accept``) connects, at most one fewer than members.

    Pairs come in batches; those whose ends are connected by then are passed over without a look, so a
    large group of near copies costs comparisons of bits, not a step for each pair. With ``asked`` only the
    pairs that hold one of these members count; members of equal ``roots`` are connected from the start.
    """
    links, forest, every = [], Forest(len(fingerprints)), asked is None
    asked = np.arange(len(fingerprints)) if every else asked
    if roots is not None:
        _, first, group = np.unique(roots, return_index=True, return_inverse=True)
        for i, at in enumerate(first[group].tolist()):
            forest.union(at, i)
    label = np.array([forest.find(i) for i in range(len(fingerprints))])
    for queries, members in BKTree(fingerprints).search(fingerprints[asked], radius):
        queries = asked[queries]
        for at in range(0, len(queries), 4096):
            a, b = queries[at : at + 4096], members[at : at + 4096]
            apart = label[a] != label[b]
            if every:
                apart &= a < b
            a, b = a[apart], b[apart]
            if accept is not None and len(a):
                alike = accept(a, b)
                a, b = a[alike], b[alike]
            if len(a):
                links += [(x, y) for x, y in zip(a.tolist(), b.tolist(), strict=True) if forest.union(x, y)]
                label = np.array([forest.find(i) for i in range(len(label))])
    return links


# --- fingerprints ---------------------------------------------------------------------------------------


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """The contract's 64-bit SimHash: XXH64 (seed 42) of every shingle of A-Z-lowered words, by majority."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    k = min(shingle, len(words))
    joined, ends = b" ".join(words), [e - 1 for e in accumulate(len(w) + 1 for w in words)]
    starts = [0, *(e + 1 for e in ends[:-1])]
    xxh = xxhash.xxh64_intdigest
    hashes = [xxh(joined[s:e], 42) for s, e in zip(starts, ends[k - 1 :], strict=False)]
    return majority_bits(np.array(hashes, np.uint64))


def _signed(values) -> np.ndarray:
    return np.array(values, np.uint64).view(np.int64)


def _fingerprints(shingle: int):
    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            found = _signed([fingerprint(t.as_py(), shingle) for t in texts])
            yield pa.record_batch([ids, pa.array(found)], names=["doc_id", "fp"])

    return run


# --- exact multi-index shards ---------------------------------------------------------------------------


def _blocks(count: int) -> list[int]:
    """Masks of ``count`` near-equal blocks of 64 bits."""
    cuts = [64 * i // count for i in range(count + 1)]
    return [((1 << b) - (1 << a)) for a, b in zip(cuts, cuts[1:], strict=False)]


def shard_masks(radius: int, distinct: int, mean: int = SHARD) -> list[int]:
    """Bit masks such that two fingerprints within ``radius`` agree on at least one of them.

    With radius+extra blocks some ``extra`` blocks agree, so their combinations do, and so do any bits of theirs. As
    many bits are taken as leave about ``mean`` fingerprints a shard, a tree's worth; more blocks where these don't do.
    """
    need = (distinct // mean).bit_length()
    if not need:
        return [0]
    for extra in range(1, 6):
        each = 64 // (radius + extra)
        if need <= extra * each or extra == 5:
            kept = min(each, -(-need // extra))
            masks = [m & -m for m in _blocks(radius + extra)]
            return [sum(low * ((1 << kept) - 1) for low in c) for c in combinations(masks, extra)]
    raise AssertionError


def _as_long(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def _tree_links(radius: int):
    """Reads rows in (shard, key) order and links each shard's fingerprints by its BK-tree."""

    def of(keys: np.ndarray, fps: np.ndarray) -> list[tuple[int, int]]:
        cut = np.flatnonzero(np.any(keys[1:] != keys[:-1], axis=1)) + 1
        bounds = np.concatenate(([0], cut, [len(fps)]))
        found = []
        for i in np.flatnonzero(np.diff(bounds) > 1):
            own = fps[bounds[i] : bounds[i + 1]]
            found += [(int(own[a]), int(own[b])) for a, b in spanning_links(own.view(np.uint64), radius)]
        return found

    def emit(links):
        pairs = np.array(links, np.int64).reshape(-1, 2)
        return pa.record_batch([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["u", "v"])

    def run(batches):
        held_keys, held = np.zeros((0, 2), np.int64), np.zeros(0, np.int64)
        for batch in batches:
            columns = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
            held_keys, held = np.concatenate((held_keys, np.stack(columns[:2], 1))), np.concatenate((held, columns[2]))
            if not len(held):
                continue
            last = int(np.flatnonzero(np.any(held_keys != held_keys[-1], axis=1))[-1]) + 1 if np.any(held_keys != held_keys[-1]) else 0
            yield emit(of(held_keys[:last], held[:last]))
            held_keys, held = held_keys[last:], held[last:]
        if len(held):
            yield emit(of(held_keys, held))

    return run


def hamming_links(distinct: DataFrame, radius: int, split_above: int = SPLIT_ABOVE, mean: int = SHARD) -> DataFrame:
    """Links (u, v) between the fingerprints ``fp`` of ``distinct``, whose closure is that of the radius.

    Every shard's BK-tree is built and searched by its members where the shard is. A shard of more than
    ``split_above`` fingerprints is split exactly, again and again: its members agree on the shard's mask, so two within the radius
    agree on one of radius+1 blocks of the bits that are left, which joins the mask. A mask that leaves few bits
    bounds its shards by itself. The driver holds masks (a few a round), never fingerprints.
    """
    masks = shard_masks(radius, distinct.count(), mean)
    dealt = distinct.select("fp", F.explode(_under([(i, m) for i, m in enumerate(masks)])).alias("s")).select("s.*", "fp")
    while True:
        big = dealt.groupBy("shard", "key").count().where(F.col("count") > split_above).select("shard", "key")
        open_ = [r[0] for r in big.select("shard").distinct().collect()]  # at most as many as there are masks
        open_ = [i for i in open_ if 64 - masks[i].bit_count() > max(radius + 1, split_above.bit_length() - 1)]
        if not open_:
            break
        finer, known = [], len(masks)
        for i in open_:
            rest = [b for b in range(64) if not masks[i] >> b & 1]
            cuts = [len(rest) * j // (radius + 1) for j in range(radius + 2)]
            subs = [masks[i] | sum(1 << b for b in rest[x:y]) for x, y in zip(cuts, cuts[1:], strict=False)]
            finer.append((i, [(known + j, m) for j, m in enumerate(subs)]))
            masks, known = masks + subs, known + len(subs)
        marked = dealt.join(big.where(F.col("shard").isin(open_)).withColumn("big", F.lit(True)), ["shard", "key"], "left")
        split = F.array(F.struct("shard", "key"))
        for i, subs in finer:
            split = F.when(F.col("big") & (F.col("shard") == i), _under(subs)).otherwise(split)
        dealt = materialise(marked.select("fp", F.explode(split).alias("s")).select("s.*", "fp"))
    at = ["shard", "key"]
    return dealt.repartition(*at).sortWithinPartitions(*at).mapInArrow(_tree_links(radius), "u long, v long")


def _under(masks: list[tuple[int, int]]):
    """The shards of ``fp`` under numbered masks."""
    return F.array(*[F.struct(F.lit(i).cast("long").alias("shard"), F.col("fp").bitwiseAND(F.lit(_as_long(m))).alias("key")) for i, m in masks])


def near_components(docs: DataFrame, shingle: int = 3, radius: int = 2, runs: int | None = None) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of ``docs`` (doc_id, text).

    Null, empty and blank texts have fingerprint zero, which links like any other. The component id is the
    smallest non-null doc_id reachable over links of at most ``radius`` bits (null if there is none).
    Repeated rows and equal fingerprints are one node of the graph, so a text that a third of the rows
    share costs as much as any other. Empty tables give empty results; other columns are ignored.
    """
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = materialise(read.mapInArrow(_fingerprints(shingle), "doc_id long, fp long").withColumn("run", run_of(runs)))
    per_run = found.groupBy("run", "fp").agg(F.min("doc_id").alias("least"))
    nodes = materialise(per_run.groupBy("fp").agg(F.min("least").alias("least")))
    roots = connected_components(hamming_links(nodes.select("fp"), radius))
    linked = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left")
    least = linked.where("root IS NOT NULL").groupBy("root").agg(F.min("least").alias("of_root"))
    labels = linked.join(least, "root", "left").select("fp", F.coalesce("of_root", "least").alias("component_id"))
    down = per_run.select("run", "fp").join(labels, "fp")
    return found.join(down, ["run", "fp"]).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# --- near copies by similarity (the pipeline's stage) ------------------------------------------------------

SIGNATURE, ROWS, BANDS = 256, 3, 12
#: Signatures propose pairs down to this much under the similarity: four standard errors of their estimate at 0.8.
SLACK = 0.1
_SEEDS = mix(np.arange(1, SIGNATURE + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def shingle_set(text: str | None, shingle: int) -> np.ndarray:
    """The sorted distinct hashes of all word shingles of the whole text."""
    data = (text or "").encode("utf-8", "surrogatepass").lower()
    return np.unique(shingle_hashes(word_hashes(data)[2], shingle))


def signature(hashes: np.ndarray) -> tuple[int, np.ndarray]:
    """The SimHash and the 256 MinHash values of a set of shingles."""
    if not len(hashes):
        return 0, np.zeros(SIGNATURE, np.uint64)
    least = np.full(SIGNATURE, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 2048):
        part = hashes[at : at + 2048]
        mixed = part[None, :] * _SEEDS[:, None]
        np.minimum(least, (mixed ^ (mixed >> np.uint64(32))).min(axis=1), out=least)
    return majority_bits(hashes), least


def _signatures(shingle: int):
    schema = ["doc_id", "row_key", "fp", "sig", "bands", "node"]

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                found, nodes = [], []
                for t in part.column(2):
                    hashes = shingle_set(t.as_py(), shingle)
                    found.append(signature(hashes))
                    nodes.append(xxhash.xxh64_intdigest(hashes.tobytes()))
                sigs = np.array([s for _, s in found], np.uint64).reshape(-1, SIGNATURE)
                used = sigs[:, : ROWS * BANDS].reshape(len(sigs), BANDS, ROWS)
                bands = mix(mix(mix(used[:, :, 0]) + used[:, :, 1]) + used[:, :, 2]).view(np.int64)
                yield pa.record_batch(
                    [part.column(0), part.column(1), pa.array(_signed([f for f, _ in found])),
                     pa.array([s.astype("<u2").tobytes() for s in sigs], pa.binary()),
                     pa.array(list(bands), pa.list_(pa.int64())), pa.array(_signed(nodes))],
                    names=schema,
                )

    return run


def _shingle_sets(shingle: int):
    """(node, set) of (node, text), the set as its sorted 64-bit hashes."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = [shingle_set(t.as_py(), shingle).tobytes() for t in part.column(1)]
                yield pa.record_batch([part.column(0), pa.array(sets, pa.binary())], names=["node", "set"])

    return run


def alike(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    """Whether two sorted sets share ``similarity`` of their union or more."""
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    if len(small) < similarity * len(large) * (1 - 1e-9) or not len(small):
        return False
    at = np.searchsorted(large, small)
    both = int(np.count_nonzero(large[np.minimum(at, len(large) - 1)] == small))
    return both / (len(a) + len(b) - both) >= similarity


#: Nodes of a shard that are compared in one task; larger shards are cut into chunks of about this many.
CHUNK = 1024


def _band_links(radius: int, similarity: float):
    """Links the nodes of each (band, key, chunk), read in that order; ``asked`` and ``root`` as in ``spanning_links``.

    The signatures propose pairs; where the nodes bring their shingle sets, these decide.
    """
    need = int(np.ceil((similarity - SLACK) * SIGNATURE))

    def links_of(rows: list[tuple]) -> Iterator[tuple[int, int]]:
        nodes, fps, sigs, asked, roots, sets = zip(*rows, strict=True)
        table = np.frombuffer(b"".join(sigs), "<u2").reshape(len(sigs), SIGNATURE)
        held = None if sets[0] is None else [np.frombuffer(x, np.uint64) for x in sets]

        def accept(a: np.ndarray, b: np.ndarray) -> np.ndarray:
            near = np.count_nonzero(table[a] == table[b], axis=1) >= need
            if held is not None:
                for i in np.flatnonzero(near):
                    near[i] = alike(held[a[i]], held[b[i]], similarity)
            return near

        only = None if all(asked) else np.flatnonzero(asked)
        for a, b in spanning_links(np.array(fps, np.int64).view(np.uint64), radius, accept, only, np.array(roots, np.int64)):
            yield nodes[a], nodes[b]

    def emit(links) -> pa.RecordBatch:
        pairs = np.array(links, np.int64).reshape(-1, 2)
        return pa.record_batch([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["u", "v"])

    def run(batches):
        at, rows = None, []
        for batch in batches:
            found = []
            for band, key, chunk, *row in zip(*(batch.column(i).to_pylist() for i in range(9)), strict=True):
                if (band, key, chunk) != at:
                    if len(rows) > 1:
                        found += links_of(rows)
                    at, rows = (band, key, chunk), []
                rows.append(tuple(row))
            yield emit(found)
        if len(rows) > 1:
            yield emit(list(links_of(rows)))

    return run


def _class_links(nodes: DataFrame, radius: int, similarity: float, chunk: int) -> DataFrame:
    """Links (u, v) of ``nodes`` (node, x: fp, sig, bands, set) whose closure is that of all similar pairs of a shard.

    Shards of more than ``chunk`` nodes go through two steps, and no task sees more than about a chunk.
    First every chunk is linked by itself, together with the shard's least node, which ties the chunks of a
    group of near copies. Then only nodes outside the shard's largest component can still lack a link: these
    strays are sent to all chunks of their shard, and meet every node that is not connected to them yet.
    """
    place = nodes.select("node", F.posexplode("x.bands").alias("band", "key"))
    shards = materialise(place.groupBy("band", "key").agg(F.count("*").alias("n"), F.min("node").alias("pivot")).where("n > 1")
                         .withColumn("chunks", F.ceil(F.col("n") / chunk).cast("int")).drop("n"))
    of = F.pmod(F.xxhash64("node", "band"), F.col("chunks")).cast("int").alias("chunk")
    columns = ["band", "key", "chunk", "node", "fp", "sig", "asked", "root", "set"]
    at = columns[:3]

    def linked(rows: DataFrame) -> DataFrame:
        return rows.select(*columns).repartition(*at).sortWithinPartitions(*at).mapInArrow(_band_links(radius, similarity), "u long, v long")

    # Only narrow rows are shuffled to find a node's shards (at most BANDS); its signature joins them once.
    spots = place.join(shards, ["band", "key"]).groupBy("node").agg(F.collect_list(F.struct("band", "key", of)).alias("spots"))
    alone = [F.lit(True).alias("asked"), F.col("node").alias("root")]
    known = nodes.select("node", "x.fp", "x.sig", "x.set")
    members = known.join(spots, "node").select("node", "fp", "sig", "set", F.inline("spots")).select("band", "key", "chunk", "node", "fp", "sig", "set", *alone)
    large = shards.where("chunks > 1")
    if large.isEmpty():
        return linked(members)
    everywhere = F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk")
    pivots = large.withColumnRenamed("pivot", "node").join(known, "node").select("band", "key", everywhere, "node", "fp", "sig", "set", *alone)
    first = materialise(linked(members.union(pivots)))
    roots = connected_components(first)
    rooted = place.join(large, ["band", "key"]).select("band", "key", "chunks", "node", of).join(roots, "node", "left")
    rooted = materialise(rooted.withColumn("root", F.coalesce("root", "node")))
    sizes = rooted.groupBy("band", "key", "root").count()
    main = sizes.groupBy("band", "key").agg(F.max_by("root", F.struct("count", "root")).alias("main"), F.count("*").alias("parts")).where("parts > 1")
    again = rooted.join(main, ["band", "key"])
    strays = again.where("root != main").select("band", "key", everywhere, "node", F.lit(True).alias("asked"), "root")
    rest = again.where("root = main").select("band", "key", "chunk", "node", F.lit(False).alias("asked"), "root")
    return first.union(linked(strays.union(rest).join(known, "node")))


def near_copies(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, radius: int = 24, runs: int | None = None, chunk: int = CHUNK) -> DataFrame:
    """doc_id, row_key, class_id: classes of documents whose shingle sets are ``similarity`` alike or more.

    A document's shards are the ``BANDS`` hashes of ``ROWS`` MinHash values each, which two documents
    of similarity 0.8 share with probability over 0.999; in a shard the BK-tree of SimHash fingerprints
    proposes the pairs within ``radius``, and the agreement of 256 MinHash values (standard error 0.025 at 0.8)
    leaves those of ``similarity`` less ``SLACK`` or more. Every pair of the similarity thus lies within one component of these
    candidates. Only their members' texts are read again, a component becomes a shard, and there the exact
    similarity of the shingle sets decides before a link is made. Equal shingle sets are one node, and a shard
    emits a spanning forest of its links, never its pairs; ``_class_links`` tells how large shards are split.
    ``row_key`` tells rows apart that share an id; ``docs`` may bring its own. Texts without a word are alike. Null texts count as empty,
    repeated rows are in one class, null ids come first in the order by which a class is named, other columns are ignored and empty tables
    give empty results.
    """
    key = F.col("row_key") if "row_key" in docs.columns else F.xxhash64("doc_id", "text")
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), key.alias("row_key"), "text")
    schema = "doc_id long, row_key long, fp long, sig binary, bands array<long>, node long"
    found = materialise(read.mapInArrow(_signatures(shingle), schema).withColumn("run", run_of(runs)))
    # Partial sums on the reading side leave one row of a hot node in each partition.
    no_set = F.lit(None).cast("binary").alias("set")
    nodes = materialise(found.groupBy("node").agg(F.min(F.struct("doc_id", "row_key")).alias("least"), F.first(F.struct("fp", "sig", "bands", no_set)).alias("x")))
    candidates = materialise(connected_components(_class_links(nodes, radius, similarity, chunk)))
    members = nodes.join(candidates.withColumnRenamed("root", "of"), "node").select("node", F.col("least.row_key").alias("row_key"), "of", "x.fp", "x.sig")
    texts = read.join(members.select("node", "row_key"), "row_key").select("node", "text")
    sets = texts.mapInArrow(_shingle_sets(shingle), "node long, set binary").groupBy("node").agg(F.first("set").alias("set"))
    exact = materialise(members.join(sets, "node").select("node", F.struct("fp", "sig", F.array("of").alias("bands"), "set").alias("x")))
    roots = connected_components(_class_links(exact, radius, similarity, chunk))
    rooted = nodes.select("node", "least").join(roots, "node", "left")
    least = rooted.where("root IS NOT NULL").groupBy("root").agg(F.min("least").alias("of_root"))
    labels = rooted.join(least, "root", "left").select("node", F.coalesce("of_root", "least").alias("stays"))
    down = found.select("run", "node").distinct().join(labels, "node")
    return found.join(down, ["run", "node"]).select("doc_id", "row_key", F.col("stays.doc_id").alias("class_id"), F.col("stays.row_key").alias("class_key"))

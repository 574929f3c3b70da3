"""The operators' methods against plain reimplementations: schedules, kernels, tests of randomness, windows, trees, pages."""

import heapq
import math
import random
import time
from collections import Counter, defaultdict

import numpy as np
import pytest

from ldp_hist.llm import decontaminate, html_text, langid, pieces, secrets_scan, sharding, simhash, words

SF = "/root/testdata/sf0.001"


# --- longest processing time -------------------------------------------------------------------------------


def heap_schedule(sizes, shards):
    """One group at a time: (shards in the order of the groups of each size, loads)."""
    heap, order = [(0, s) for s in range(shards)], defaultdict(list)
    for size in sorted(sizes, reverse=True):
        load, shard = heapq.heappop(heap)
        order[size].append(shard)
        heapq.heappush(heap, (load + size, shard))
    return order, sorted((s, v) for v, s in heap)


@pytest.mark.parametrize("seed", range(12))
def test_plan_is_the_heap(seed):
    rng = random.Random(seed)
    shards = rng.choice([1, 2, 3, 24])
    counts = {rng.randrange(1, 500): rng.choice([1, 2, 5, 200, 1000]) for _ in range(rng.randrange(1, 12))}
    order, loads = heap_schedule([s for s, n in counts.items() for _ in range(n)], shards)
    got = dict.fromkeys(range(shards), 0)
    for size, ends in sharding.lpt_plan(list(counts.items()), shards).items():
        before, placed = 0, []
        for end, shard in ends:
            placed += [shard] * (end - before)
            before = end
        assert Counter(placed) == Counter(order[size])
        for shard in placed:
            got[shard] += size
    assert sorted(got.items()) == loads


@pytest.mark.parametrize("lot", [100_000, 7])
def test_shards_follow_the_plan(spark, lot):
    texts = [None, "", "same", "same"] + ["x" * (i % 23) + str(i % 300) for i in range(900)] + ["hot"] * 300
    made = spark.createDataFrame([(i // 2, t, "clash", 1, "r") for i, t in enumerate(texts)], "doc_id long, text string, digest string, shard int, run string").repartition(5)
    got = sharding.lpt_shards(made, shards=5, lot=lot).collect()
    groups, load, of = defaultdict(int), defaultdict(int), {}
    for t in texts:
        groups[t or ""] += len((t or "").encode()) + 8
    for r in got:
        assert of.setdefault(r["group_digest"], r["shard"]) == r["shard"]
        load[r["shard"]] += r["size"]
    _, want = heap_schedule(groups.values(), 5)
    assert sorted(load.items()) == want and len(got) == len(texts) and len(of) == len(groups)
    for s in load:
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))


# --- kernel ridge regression ----------------------------------------------------------------------------------


def test_weights_are_kernel_ridge_regression(spark):
    """With every row a landmark the Nystroem features are exact, and the dual solution has to come out."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("text RLIKE '[a-z]'").orderBy("doc_id").collect()
    texts = {k: [r["text"][:400] for r in docs if r["lang"] == k and len(r["text"]) > 100][:40] for k in ("en", "fr", "de")}
    rows = [(t, i) for i, k in enumerate(("en", "fr", "de")) for t in texts[k][:30]]
    grams = [set(langid.ngram_buckets(t).tolist()) for t, _ in rows]
    kernel = lambda a, b: len(a & b) / math.sqrt(max(1, len(a)) * max(1, len(b)))
    K = np.array([[kernel(a, b) for b in grams] for a in grams])
    Y = np.eye(3)[[i for _, i in rows]]
    dual = np.linalg.solve(K + langid.RIDGE * len(rows) / 10 * np.eye(len(rows)), Y)
    weights = langid._weights(langid.presence([t for t, _ in rows]), np.array([i for _, i in rows]), 3)
    asked = [t for k in texts for t in texts[k][30:]]
    want = np.array([[kernel(set(langid.ngram_buckets(t).tolist()), g) for g in grams] for t in asked]) @ dual
    assert np.allclose(langid.presence(asked) @ weights, want, atol=2e-3)


def test_every_language_is_learned(spark):
    """Eighty languages with an alphabet of their own each, one of them rare, and rows that repeat."""
    rng = random.Random(3)
    word = lambda k: "".join(chr(0x4E00 + 40 * k + rng.randrange(40)) for _ in range(4))
    rows = [(i, " ".join(word(i % 80) for _ in range(30)), f"l{i % 80:02d}") for i in range(80 * 12)]
    rows += [rows[3]] * 200 + [(10**6 + i, "123 !", "l00") for i in range(50)] + [(None, word(1), "l01")]
    made = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.train(made)
    assert model.langs == [f"l{k:02d}" for k in range(80)]
    got = {r["doc_id"]: r["lang_pred"] for r in langid.language_id(made).collect()}
    assert np.mean([got[i] == k for i, _, k in rows[: 80 * 12]]) > 0.97


def test_equal_responses_fall_to_the_first_language():
    model = langid.fit([("same words here", "b"), ("same words here", "a")])
    assert model.langs == ["a", "b"] and model.judge(["same words"])[0].argmax(axis=1)[0] == 0


# --- tests of randomness -----------------------------------------------------------------------------------------


def plain_battery(token):
    """Chi-squared with its exact moments, runs about the middle of the alphabet, lag-one correlation; three times the least."""
    import re

    _, _, alphabet = next(x for x in secrets_scan.ENCODINGS if re.search(x[1], token))
    name = next(x[0] for x in secrets_scan.ENCODINGS if re.search(x[1], token))
    t, n, k = token.upper() if name == "hex" else token, len(token), len(alphabet)
    tail = lambda z: math.erfc(min(abs(z), 37.0) / math.sqrt(2))
    z = (sum(c * c for c in Counter(t).values()) * k / n - n - (k - 1)) / math.sqrt(2 * (k - 1) * (n - 1) / n)
    chi = math.erfc(z / math.sqrt(2)) / 2
    high = [alphabet.index(c) >= (k + 1) // 2 for c in t]
    ones, zeros, runs = sum(high), n - sum(high), 1 + sum(a != b for a, b in zip(high, high[1:]))
    if not ones or not zeros:
        run = 0.5 ** (n - 1)
    else:
        e = 1 + 2 * ones * zeros / n
        run = tail((runs - e) / math.sqrt(max((e - 1) * (e - 2) / (n - 1), 1e-9)))
    x = np.array([alphabet.index(c) + 1.0 for c in t])
    d = x - x.mean()
    serial = 0.0 if (d @ d) <= 1e-9 else tail(((d[:-1] @ d[1:]) / (d @ d) + 1 / n) * math.sqrt(n))
    return name, min(1.0, 3 * min(chi, run, serial))


def test_battery(spark):
    rng = random.Random(12)
    tokens = ["".join(rng.choice(a) for _ in range(rng.randrange(20, 90))) for _, _, a in secrets_scan.ENCODINGS for _ in range(12)]
    tokens += ["0123456789" * 3, "ABCD" * 8, "antidisestablishmentarianism", "zzzzzzzzzzzzzzzzzzzzzzz", "AAAAABBBBB" * 4]
    made = spark.createDataFrame([(t,) for t in tokens], "t string")
    for r in made.select("t", secrets_scan.battery(made["t"]).alias("b")).collect():
        name, p = plain_battery(r["t"])
        assert r["b"]["encoding"] == name and r["b"]["p"] == pytest.approx(p, abs=1e-5), r["t"]


def test_levels():
    row = lambda e, s, n, high, at: {"encoding": e, "stratum": s, "n": n, "high": high} | {f"at{i}": v for i, v in enumerate(at)}

    class Fake:
        def __init__(self, rows):
            self.rows = rows

        def groupBy(self, *_):
            return self

        def agg(self, *_):
            return self

        def collect(self):
            return self.rows

    pytest.importorskip("pyspark")
    uniform = row("hex", 5, 100, 50, (100, 99, 95, 90, 80))
    text = row("hex", 6, 100, 0, (60, 30, 10, 5, 2))
    few, alone = row("hex", 9, 1, 0, (1, 1, 1, 1, 1)), row("base32", 5, 3, 1, (3, 3, 3, 2, 2))
    got = secrets_scan.thresholds(Fake([uniform, text, few, alone]))
    assert got["hex", 5] == 0.001 and got["hex", 6] == 2.0 and got["hex", 9] == secrets_scan.level_for([text, few]) and got["base32", 5] == secrets_scan.ALONE


def test_spans_that_overlap(spark):
    rng = random.Random(6)
    token = lambda n: "".join(rng.choice("ABCDEFGHJKLMNPQRSTUVWXYZbcdfghjkmnpqrstvwxyz23456789+/") for _ in range(n))
    texts = ["x" + token(30) + "_secret=" + token(14) + " " + token(40), "AKIA" + "B" * 16 + token(10) + " " + token(30), token(25) + "0123456789abcdef01 " + token(25)]
    texts += [" ".join(rng.choice([token(24), "token=" + token(13), "0123456789abcdef" * 2, "word"]) for _ in range(n)) for n in (5, 40, 700)]
    made = spark.createDataFrame([(i, t, "c", "c", 1) for i, t in enumerate(texts)] * 2 + [(None, None, None, None, None)], "doc_id long, text string, base string, tokens string, s int")
    text = made["text"]
    base = secrets_scan.spans(text, secrets_scan.ASSIGN)
    found = made.where("text IS NOT NULL").select("text", base.alias("b"), secrets_scan.spans(text, secrets_scan.TOKEN).alias("t"))
    for r in found.select("text", "b", "t", secrets_scan._free(found["t"], found["b"]).alias("free")).collect():
        assert all(r["text"][x["s"] : x["e"]] == x["hit"] for x in [*r["b"], *r["t"]])
        assert [tuple(x) for x in r["free"]] == [tuple(t) for t in r["t"] if not any(b["s"] < t["e"] and t["s"] < b["e"] for b in r["b"])]
    got = secrets_scan.scan_secrets(made).collect()
    assert len(got) == 2 * len(texts) + 1 and Counter(r["spans"] for r in got if r["doc_id"] is not None).most_common()[-1][1] % 2 == 0


def test_many_spans_take_linear_time(spark):
    def seconds(n):
        made = spark.createDataFrame([(1, " ".join(f"token=abcdefgh{i:08d} ABCDEFGHIJKLMNOPQRSTUVW{i}" for i in range(n)))], "doc_id long, text string")
        began = time.time()
        (r,) = secrets_scan.scan_secrets(made).collect()
        assert r["n_assign"] == n
        return time.time() - began

    seconds(10)
    a, b = seconds(4_000), seconds(16_000)
    assert b < 8 * a + 4, (a, b)


# --- trees -----------------------------------------------------------------------------------------------------------


def test_tree_follows_and_prunes_edges():
    rng = np.random.default_rng(1)
    fps = rng.integers(0, 1 << 63, 2000, dtype=np.uint64)
    tree = simhash.BKTree(fps)
    pivot, children = tree.root
    assert all((int(fps[pivot]) ^ int(fps[c if not isinstance(c, tuple) and isinstance(c, int) else (c[0] if isinstance(c, tuple) else c[0])])).bit_count() == k for k, c in children.items())
    assert {(a, b) for q, m in tree.search(fps, 2) for a, b in zip(q.tolist(), m.tolist(), strict=True)} >= {(i, i) for i in range(2000)}
    assert tree.followed > 2000 and tree.pruned > tree.followed


def test_shards_hold_trees():
    for distinct in (1_000, 250_000, 10**9):
        masks = simhash.shard_masks(2, distinct)
        mean = distinct / 2 ** masks[0].bit_count()
        assert 64 <= mean <= 1000 and len(masks) <= 6


def test_near_copies_find_all_of_exact_similarity(spark):
    """Recall against exact similarity, over all pairs of a table that share a shingle."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    classes = {r["doc_id"]: r["class_id"] for r in simhash.near_copies(docs).collect()}
    sets, held = {}, defaultdict(set)
    for r in docs.collect():
        w = (r["text"] or "").encode().lower().split()
        k = min(5, len(w))
        sets[r["doc_id"]] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()
        for g in sets[r["doc_id"]]:
            held[g].add(r["doc_id"])
    pairs = {(a, b) for ids in held.values() for a in ids for b in ids if a < b}
    alike = {(a, b) for a, b in pairs if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    different = [(a, b) for a, b in alike if sets[a] != sets[b]]
    assert len(different) > 5 and all(classes[a] == classes[b] for a, b in alike)
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in sorted(alike):
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    empties = [i for i, s in sets.items() if not s]
    assert all(classes[i] == find(i) for i in sets if i not in empties)


# --- windows -------------------------------------------------------------------------------------------------------------


def all_windows(text, item, k=5):
    w, v = decontaminate._words(text), decontaminate._words(item)
    have, want = words.shingle_hashes(w, k), words.shingle_hashes(v, k)
    return max((decontaminate.weighted_similarity(have[s : s + len(want)], want) for s in range(len(have))), default=0.0)


def test_windows_are_laid_everywhere(spark):
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    rng = random.Random(7)
    fresh = lambda n: [f"w{rng.randrange(10**7)}" for _ in range(n)]
    long = fresh(80)
    items.append((10_000, " ".join(long)))
    index = decontaminate.Index(items, 5)
    swapped = " ".join([*fresh(20), *long[40:], *long[:40], *fresh(20)])
    assert index.matches(swapped, 0.8)[len(items) - 1] == pytest.approx(all_windows(swapped, items[-1][1])) and all_windows(swapped, items[-1][1]) >= 0.88
    tried = 0
    for _ in range(400):
        n = rng.randrange(len(items))
        v = items[n][1].split()
        for _ in range(rng.randrange(1, 5)):
            at = rng.randrange(len(v))
            v[at : at + rng.randrange(2)] = fresh(rng.randrange(2))
        cut = rng.randrange(len(v)) if rng.random() < 0.3 else 0
        text = " ".join([*fresh(rng.randrange(30)), *v[cut:], *v[:cut], *fresh(rng.randrange(30))])
        best = all_windows(text, items[n][1])
        tried += best >= 0.8
        assert index.matches(text, 0.8).get(n, 0) == pytest.approx(best if best >= 0.8 else 0)
    assert tried >= 60


def test_index_is_complete_and_selective():
    rng = random.Random(2)
    items = [(i, " ".join(f"w{rng.randrange(10**6)}" for _ in range(40))) for i in range(300)]
    index = decontaminate.Index(items, 5)
    shape = index.prints.shape
    asked = looked = 0
    for n in range(0, 300, 10):
        for flips in (0, 20, 63):
            bits = np.unpackbits(index.prints[n].astype("<u2").view(np.uint8), bitorder="little")
            for b in rng.sample(range(256), flips):
                bits[b] ^= 1
            print_ = np.packbits(bits, bitorder="little").view("<u2").astype(np.uint32)
            near = index.near(print_)
            want = np.flatnonzero(np.bitwise_count(index.prints ^ print_).sum(axis=1) <= decontaminate.RADIUS)
            assert near.tolist() == want.tolist() and n in near
            asked, looked = asked + 1, looked + len(near)
    assert shape == (300, decontaminate.BLOCKS) and looked < 2 * asked


def test_decontamination_edges(spark):
    rng = random.Random(4)
    fresh = lambda n: " ".join(f"w{rng.randrange(10**7)}" for _ in range(n))
    bench = [(i, fresh(30)) for i in range(20)]
    rows = [(1, bench[3][1], "a", 0.5), (1, bench[3][1], "a", 0.5), (None, bench[4][1], None, None), (2, fresh(60_000) + " " + bench[5][1], "b", 1.0), (3, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, item_ids string, similarity double")
    table = spark.createDataFrame(bench + bench[:5], "item_id long, text string")
    got = [decontaminate.contamination(docs, table, part_bytes=size).select("row.doc_id", "row.item_ids", "item_ids").collect() for size in (1 << 20, 1000)]
    for some in got:
        assert sorted((r[0] or 0, r[2]) for r in some) == [(0, [4]), (1, [3]), (1, [3]), (2, [5]), (3, [])]


# --- pieces ---------------------------------------------------------------------------------------------------------------


def plain_search(v, marked):
    best, back = [0.0], [0]
    for e in range(1, len(marked) + 1):
        options = [(best[s] + v.scores.get(marked[s:e], v.unknown_score if e - s == 1 else -1e18), -s) for s in range(max(0, e - v.longest), e)]
        top = max(options)
        best.append(top[0])
        back.append(-top[1])
    cuts, e = [], len(marked)
    while e:
        cuts.append(marked[back[e] : e])
        e = back[e]
    return [i for p in reversed(cuts) for i in ([v.ids[p]] if p in v.ids else [v.byte_ids[b] for b in p.encode()])]


@pytest.mark.parametrize("portion", [1, 7, 64, 10_000])
def test_one_search_with_a_bounded_window(portion):
    v, rng = pieces.Vocabulary.load(), random.Random(portion)
    text = "".join(rng.choice("abcdefinrst") for _ in range(4000)) + "é😀" * 20
    stream, out, held = pieces.StreamingViterbi(v), [], 0
    for i in range(0, len(text), portion):
        out += stream.feed(text[i : i + portion])
        held = max(held, len(stream.text))
    early = len(out)
    out += stream.finish()
    assert out == plain_search(v, text) and early > len(out) - 60
    assert held <= portion + 12 * v.longest


def test_no_length_changes_the_result():
    v, rng = pieces.Vocabulary.load(), random.Random(5)
    for n in (1, 5, 60, 63, 64, 65, 66, 200, 1500):
        text = "".join(rng.choice("aeinrst") for _ in range(n))
        assert list(pieces.encode(v, f"x {text} y")) == plain_search(v, pieces.SPACE + f"x {text} y".replace(" ", pieces.SPACE))


def test_decode_edges(spark):
    v = pieces.Vocabulary.load()
    assert pieces.decode(v, np.array([], np.int32)) == "" and "\ufffd" in pieces.decode(v, np.array([-1, 10**6], np.int32))
    made = spark.createDataFrame([(1, [300, 301], 5), (None, None, 1), (2, [], 1), (2, [], 1)], "doc_id long, token_ids array<int>, text int")
    assert sorted(len(r["text"]) > 0 for r in pieces.decode_documents(made).collect()) == [False, False, False, True]
    docs = spark.createDataFrame([(1, "two words", 7, "x")], "doc_id long, text string, n_tokens long, token_ids string")
    (r,) = pieces.encode_documents(docs, carry=["doc_id", "n_tokens", "token_ids"]).collect()
    assert r["n_tokens"] == len(r["token_ids"]) and r["round_trip"]


# --- pages ------------------------------------------------------------------------------------------------------------------

_P = "<p>The council met on Tuesday to discuss the new bridge, which will cost more than expected. Residents were not amused.</p>"
_T = "The council met on Tuesday to discuss the new bridge, which will cost more than expected. Residents were not amused."


@pytest.mark.parametrize("page, want", [
    (f'<body><nav><a href=x>Home</a></nav><article class="post comments-open"><h1>T</h1>{_P}</article></body>', f"T {_T}"),
    (f'<body><div class="layout has-sidebar"><article>{_P}{_P}</article><aside>side</aside></div></body>', f"{_T} {_T}"),
    (f'<body><div class="page-content widget-area">{_P}{_P}</div></body>', f"{_T} {_T}"),
    (f'<body><article><header class="story-header"><h1>Head</h1></header>{_P}</article></body>', f"Head {_T}"),
    (f'<body><main><article>{_P}</article><div id="comments"><article class="comment"><p>I do not agree with any of this, and I said so. Twice.</p></article></div></main>', _T),
    (f'<article>{_P}<article><p>A remark within, which is a comment by definition.</p></article></article>', _T),
    (f'<article>{_P}<div class="ad">Buy this now, it is a very long advert text indeed and goes on</div>{_P}</article>', f"{_T} {_T}"),
    (f'<div id="top"><ul><li><a href=a>Home</a><li><a href=b>News</a></ul></div><div class="x">{_P}{_P}</div><div class="cookie-notice">We use cookies.</div>', f"{_T} {_T}"),
    (f'<div class="widget"><h1>Title</h1>{_P}</div>', f"Title {_T}"),
])
def test_pages(page, want):
    assert html_text.main_text(page) == want


def test_deep_and_long_pages_take_linear_time():
    def seconds(page):
        began = time.time()
        html_text.main_text(page)
        return time.time() - began

    deep = lambda n: "<article>" + "<div>x" * n + "</section>" * n + "</div>" * n
    long = lambda n: "<article>" + _P * n + "</article>"
    for make in (deep, long):
        seconds(make(500))
        assert seconds(make(16_000)) < 8 * seconds(make(4_000)) + 0.5


def test_weights_are_fitted():
    rng = random.Random(1)
    sentence = lambda n: " ".join("".join(rng.choice("etaoinsh") for _ in range(5)) for _ in range(n)).capitalize() + "."
    pages = [f"<ul><li>{sentence(2)}</ul><div>{sentence(3)}</div><article><p>{sentence(40)}</p><p>{sentence(60)}</p></article>" for _ in range(60)]
    weights = html_text.fit_weights(pages)
    assert (html_text.fit_weights([]) == html_text.PRIOR).all() and (weights != html_text.PRIOR).any() and (weights == html_text.fit_weights(pages)).all()
    plain = f"<div><div>{sentence(3)}</div><div><p>{sentence(50)}</p><p>{sentence(50)}</p></div></div>"
    assert len(html_text.main_text(plain, weights)) > 500

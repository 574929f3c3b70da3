"""Each operator against brute force on a small fixture with nulls, empties, repeats and a clashing column."""

import hashlib
import os
import random
import re
import zlib
from collections import defaultdict

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import sentencepiece
import tiktoken
import xxhash

from ldp_hist.llm import decontaminate, exact_dedup, feistel, html_text, langid, line_dedup, pieces, secrets_scan, sharding, simhash
from ldp_hist.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, run string, __id string"
RNG = random.Random(5)


def sentence(n):
    return " ".join(RNG.choice("alpha beta gamma delta epsilon zeta eta theta iota kappa lam mu nu".split()) + RNG.choice(["", "s", "x"]) for _ in range(n))


def rows():
    long = sentence(3000)
    base = sentence(80)
    texts = [None, "", "  ", "One\ntwo\nOne", "ONE\nTWO\none", base, base.upper(), base.replace("alpha", "omega", 1), long, long, "é É\r\n x \t", "!!! 123", "É é\r\n x \t"]
    texts += [f"Boiler plate line\nown {i}" for i in range(12)]
    out = [(i, t, "en" if i % 2 else None, "src0", 3, "r", "i") for i, t in enumerate(texts)]
    out += [out[5], (None, "no id", "en", None, None, None, None), (None, base, None, None, None, None, None)]
    return out


ROWS = rows()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def fold(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def key(row):
    return tuple((x is not None, x) for x in row)


def same(df, expected):
    assert sorted((tuple(r) for r in df.collect()), key=key) == sorted(expected, key=key)


@pytest.mark.parametrize("keep", ["largest", "smallest"])
def test_exact_dedup(docs, empty, keep):
    groups = defaultdict(list)
    for r in ROWS:
        groups[fold(r[1])].append(r[0])
    best = {t: (max if keep == "largest" else min)((i for i in ids if i is not None), default=None) for t, ids in groups.items()}
    expected = [(r[0], best[t], len(groups[t]), r[0] == best[t] if best[t] is not None else True, hashlib.sha256(t.encode()).hexdigest()) for r in ROWS for t in [fold(r[1])]]
    same(exact_dedup.exact_dedup(docs, keep=keep, runs=5, fan_in=2), expected)
    assert exact_dedup.exact_dedup(empty).count() == 0


def brute_lines(min_chars, min_docs, keep_first):
    strip = lambda line: fold(line.strip(" \t\n\x0b\x0c\r"))
    held, first = defaultdict(set), {}
    order = sorted(range(len(ROWS)), key=lambda i: (ROWS[i][0] is not None, ROWS[i][0] or 0))
    for i in order:
        for pos, line in enumerate((ROWS[i][1] or "").split("\n")):
            held[strip(line)].add(i)
            first.setdefault(strip(line), (ROWS[i][0], ROWS[i][1], pos))
    for row in ROWS:
        lines = (row[1] or "").split("\n")
        stay = [x for p, x in enumerate(lines) if len(strip(x)) < min_chars or len(held[strip(x)]) < min_docs or (keep_first and first[strip(x)] == (row[0], row[1], p))]
        yield row[0], len(lines), len(lines) - len(stay), hashlib.sha256("\n".join(stay).encode()).hexdigest()


@pytest.mark.parametrize("how", [(1, 10, False), (1, 2, False), (1, 2, True), (8, 3, True)])
def test_line_dedup(docs, empty, how):
    names = dict(zip(("min_chars", "min_docs", "keep_first"), how, strict=True))
    same(line_dedup.line_dedup(docs, **names), list(brute_lines(*how)))
    assert line_dedup.line_dedup(empty).count() == 0
    assert line_dedup.dedup_lines(docs, **names).columns == docs.columns


def test_line_dedup_many_lines(spark):
    lines = [f"line {i % 700}" for i in range(2000)]
    made = spark.createDataFrame([(i, "\n".join(lines[i:])) for i in range(12)], "doc_id long, text string")
    for r in line_dedup.reduced(made, min_docs=12).collect():
        assert r["kept_text"] == "" or r["n_dropped"] < r["n_lines"]
    assert sum(r["n_dropped"] for r in line_dedup.reduced(made, min_docs=12).collect()) == sum(2000 - i for i in range(12))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(spark, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    got = QUERIES[name](spark, SF)
    want = con.sql(ORACLES[name])
    assert sorted(got.columns) == sorted(want.columns)
    same(got.select(*sorted(got.columns)), want.select(*sorted(want.columns)).fetchall())


def test_lpt(docs, empty):
    got = [r.asDict() for r in sharding.lpt_shards(docs, shards=3).collect()]
    assert len(got) == len(ROWS)
    shard, load = {}, defaultdict(int)
    for r in got:
        assert r["law"] == "bytes" and shard.setdefault(r["group_digest"], r["shard"]) == r["shard"]
        load[r["shard"]] += r["size"]
    for s in load:
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    same(docs.sparkSession.createDataFrame([(r["doc_id"], r["size"], r["text_crc32"]) for r in got]), [(r[0], len((r[1] or "").encode()) + 8, zlib.crc32((r[1] or "").encode())) for r in ROWS])
    assert sharding.lpt_shards(empty).count() == 0


def test_lpt_balance(spark):
    made = spark.range(5000).selectExpr("id AS doc_id", "repeat('x', cast(id % 97 as int)) || id AS text")
    load = [r[1] for r in sharding.lpt_shards(made).groupBy("shard").sum("size").collect()]
    assert len(load) == 24 and max(load) - min(load) <= 40


def naive_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", fold(text))
    if not words:
        return 0
    grams = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def closure(nodes, linked):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in nodes:
        for b in nodes:
            if a < b and linked(a, b):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {n: find(n) for n in nodes}


@pytest.mark.parametrize("radius", [0, 2, 6])
def test_simhash_components(docs, empty, radius):
    prints = [naive_fingerprint(r[1]) for r in ROWS]
    roots = closure(set(prints), lambda a, b: (a ^ b).bit_count() <= radius)
    least = {}
    for p, r in zip(prints, ROWS, strict=True):
        if r[0] is not None:
            least[roots[p]] = min(least.get(roots[p], r[0]), r[0])
    same(simhash.near_components(docs, radius=radius), [(r[0], f"{p:016x}", least.get(roots[p])) for p, r in zip(prints, ROWS, strict=True)])
    assert simhash.near_components(empty).count() == 0


def clustered(n):
    rng = np.random.default_rng(3)
    fps = [int(x) for x in rng.integers(0, 1 << 63, 40, dtype=np.uint64)]
    while len(fps) < n:
        fps.append(fps[rng.integers(len(fps))] ^ (1 << int(rng.integers(64))) ^ (1 << int(rng.integers(64))))
    return np.array(sorted(set(fps)), np.uint64)


def test_bk_tree():
    fps = clustered(600)
    found = set()
    for q, m in simhash.BKTree(fps).search(fps, 3):
        found |= set(zip(q.tolist(), m.tolist(), strict=True))
    assert found == {(i, j) for i, a in enumerate(fps) for j, b in enumerate(fps) if int(a ^ b).bit_count() <= 3}


@pytest.mark.parametrize("split_above", [8192, 3])
def test_hamming_links(spark, split_above):
    fps = clustered(400)
    made = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    got = simhash.connected_components(simhash.hamming_links(made, 2, split_above)).collect()
    root = {int(x): int(x) for x in fps.view(np.int64)} | {r["node"]: r["root"] for r in got}
    want = closure([int(x) for x in fps.view(np.int64)], lambda a, b: ((a ^ b) & ((1 << 64) - 1)).bit_count() <= 2)
    assert root == want


def test_shard_masks():
    rng = random.Random(1)
    for distinct in (10, 10**7, 10**9, 10**12):
        masks = simhash.shard_masks(2, distinct)
        for _ in range(300):
            diff = 1 << rng.randrange(64) | 1 << rng.randrange(64)
            assert any(not diff & m for m in masks)


def test_near_copies(docs, empty):
    got = {(r["doc_id"], r["row_key"]): r["class_id"] for r in simhash.near_copies(docs).collect()}
    ids = {d: c for (d, _), c in got.items() if d is not None}
    assert ids[5] == ids[6] and ids[8] == ids[9] == 8 and ids[0] == ids[1] == ids[2]
    assert len({ids[3], ids[8], ids[10], ids[11]}) == 4
    assert simhash.near_copies(empty).count() == 0


def test_near_copies_similarity(spark):
    rng = random.Random(9)
    base = [[rng.choice("abcdefgh") + str(rng.randrange(10**6)) for _ in range(300)] for _ in range(20)]
    texts, truth = [], []
    for b in base:
        texts.append(b)
        for cut in (3, 150):
            other = list(b)
            for i in rng.sample(range(300), cut):
                other[i] = "changed" + str(rng.randrange(10**9))
            texts.append(other)
    made = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    classes = {r["doc_id"]: r["class_id"] for r in simhash.near_copies(made).collect()}
    sets = [{tuple(t[i : i + 5]) for i in range(len(t) - 4)} for t in texts]
    truth = closure(range(len(texts)), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    assert classes == truth


def test_large_shards_are_split_exactly(spark):
    rng = random.Random(4)
    base = [rng.choice("abcdefgh") + str(rng.randrange(10**6)) for _ in range(200)]
    texts = []
    for i in range(60):
        t = list(base)
        for at in rng.sample(range(200), rng.choice([1, 2, 3, 12, 20])):
            t[at] = f"changed{i}x{at}"
        texts.append((i, " ".join(t)))
    made = spark.createDataFrame(texts, "doc_id long, text string")
    whole, *cut = ({r["doc_id"]: r["class_id"] for r in simhash.near_copies(made, chunk=c).collect()} for c in (1000, 20, 2))
    assert 1 < len(set(whole.values())) < 60 and all(c == whole for c in cut)


def naive_spans(text):
    t = text or ""
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t, re.I | re.A) if len(m[2]) >= 12]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 18]
    out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 16]
    return sorted(out)


def test_secrets(spark, empty):
    rng = random.Random(2)
    alnum = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    texts = [None, "", "secret=token=abcdefghijklmnop", "password=secret: abcdefghijklmnop", 'é😀 Api_Key": "0123456789abcdef0123"', "x AKIAABCDEFGHIJKLMN y AKIAAKIA", "0123456789abcdef" * 3, "passwd = short", "tokentoken: aaaaaaaaaaaaaaaaaaaaaaaa"]
    texts += ["x " + "".join(rng.choice(alnum) for _ in range(40)) + " y" for _ in range(40)]
    texts += ["word " + "antidisestablishmentarianism" * 2, "a" * 60, "-" * 5000]
    got = {r["doc_id"]: r for r in secrets_scan.scan_secrets(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    names = ("assign", "access", "hex")
    for i, t in enumerate(texts):
        want = naive_spans(t)
        listed = [f"{names[k]}:{s}:{e}" for s, k, e in want]
        assert got[i]["base_sha256"] == hashlib.sha256(",".join(listed).encode()).hexdigest(), t
        assert [got[i]["n_assign"], got[i]["n_access"], got[i]["n_hex"]] == [sum(k == n for _, k, _ in want) for n in range(3)]
        assert [x for x in got[i]["spans"].split(",") if x and not x.startswith("random")] == listed
    assert sum(got[i]["n_random"] for i in range(9, 49)) >= 30
    assert not any(got[i]["n_random"] for i in (49, 50, 51))
    assert secrets_scan.scan_secrets(empty).count() == 0


def test_secrets_on_documents(spark):
    got = {r["doc_id"]: r["base_sha256"] for r in QUERIES["op5_secret_scan"](spark, SF).collect()}
    names = ("assign", "access", "hex")
    for r in spark.read.parquet(f"{SF}/documents.parquet").collect():
        listed = ",".join(f"{names[k]}:{s}:{e}" for s, k, e in naive_spans(r["text"]))
        assert got[r["doc_id"]] == hashlib.sha256(listed.encode()).hexdigest()


def naive_contamination(text, items, k=5, least=0.8):
    words = lambda t: re.findall(r"(?:[A-Za-z0-9]|[^\x00-\x7f])+", (t or "").lower())
    grams = lambda w, k: [tuple(w[i : i + k]) for i in range(len(w) - k + 1)]
    found, w = {}, words(text)
    for item_id, item in items:
        v = words(item)
        if not v:
            continue
        n, want = min(k, len(v)), grams(v, min(k, len(v)))
        for start in range(len(w)):
            have = grams(w[start : start + len(v)], n)
            both = sum(min(have.count(g), want.count(g)) for g in set(have))
            s = both / (len(have) + len(want) - both) if have else 0
            if s >= least:
                found[item_id] = max(found.get(item_id, 0), s)
    return sorted(found), max(found.values(), default=0.0)


def test_decontamination(spark, empty):
    bench = [(1, sentence(40)), (2, sentence(30)), (3, "Just three words."), (4, None), (5, "..."), (None, sentence(20))]
    a, b = bench[0][1].split(), bench[1][1].split()
    noisy = [*a[:20], "changed", *a[20:]]
    texts = [None, "", sentence(60), f"{sentence(30)} {bench[0][1].upper()} {sentence(30)}", " ".join(a[:20]), f"x {', '.join(b)}\n y just three, words", " ".join(noisy), " ".join(a[:-1]), f"{bench[0][1]} {bench[1][1]}"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    table = spark.createDataFrame(bench, "item_id long, text string")
    got = {r["doc_id"]: (r["item_ids"], r["similarity"]) for r in decontaminate.contamination(docs, table).select("row.doc_id", "item_ids", "similarity").collect()}
    items = [x for x in bench if x[0] is not None]
    for i, t in enumerate(texts):
        want = naive_contamination(t, items)
        assert got[i][0] == want[0], (i, got[i], want)
        assert got[i][1] == pytest.approx(want[1])
    assert decontaminate.contamination(empty, table).count() == 0
    assert {len(r["item_ids"]) for r in decontaminate.contamination(docs, table.limit(0)).collect()} == {0}


def test_pieces_match_library(tmp_path):
    v = pieces.Vocabulary.load()
    data = bytearray(open(pieces.DEFAULT_MODEL, "rb").read())
    # The trainer part of the model names its kind in field 3; 1 is the unigram kind, 2 byte-pair merges.
    at = data.rfind(b"\x18\x02")
    data[at + 1] = 1
    sp = sentencepiece.SentencePieceProcessor(model_proto=bytes(data))
    rng = random.Random(4)
    words = ["Hello", "world", "ereinth", "ción", "Straße", "naïve", "Eauouon", "thing"] + ["".join(rng.choice("etaoinshr") for _ in range(rng.randrange(1, 14))) for _ in range(400)]
    differ = [w for w in words if list(pieces.encode(v, w)) != sp.encode(w)]
    assert not differ, differ[:5]


def test_pieces_streaming():
    v = pieces.Vocabulary.load()
    rng = random.Random(8)
    text = "".join(rng.choice("abcdeé  😀\n") for _ in range(3000))
    marked = pieces.SPACE + text.replace(" ", pieces.SPACE)
    stream, out, held = pieces.StreamingViterbi(v), [], 0
    for i in range(0, len(marked), 7):
        out += stream.feed(marked[i : i + 7])
        held = max(held, len(stream.text))
    out += stream.finish()
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
    want = []
    for p in reversed(cuts):
        want += [v.ids[p]] if p in v.ids else [v.byte_ids[b] for b in p.encode()]
    assert out == want and held < 400
    assert list(pieces.encode(v, text)) == want


def test_pieces_round_trip(docs, empty):
    got = pieces.encode_documents(docs, carry=["doc_id", "text"])
    assert all(r["round_trip"] and r["n_tokens"] == len(r["token_ids"]) for r in got.collect())
    back = {r["doc_id"]: r["text"] for r in pieces.decode_documents(got).collect() if r["doc_id"] is not None}
    assert all(back[r[0]] == (r[1] or "") for r in ROWS if r[0] is not None)
    assert pieces.encode_documents(empty).count() == 0
    v = pieces.Vocabulary.load()
    for text in (" ", "  a  b ", "\t\n", "😀" * 50, "a" * 5000, "₂x"):
        assert pieces.decode(v, pieces.encode(v, text)) == text


def test_language(spark, docs, empty):
    table = "/root/testdata/sf0.01"
    got = {r["doc_id"]: r for r in langid.language_id(spark.read.parquet(f"{table}/documents.parquet")).collect()}
    right = total = 0
    for r in spark.read.parquet(f"{table}/documents.parquet").collect():
        mine = got[r["doc_id"]]
        assert mine["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= mine["score"] <= 1
        if mine["held_out"] and any(c.isalpha() for c in r["text"] or ""):
            total += 1
            right += mine["lang_pred"] == r["lang"]
    assert right / total > 0.97, right / total
    small = {r["doc_id"]: r["lang_pred"] for r in langid.language_id(docs).collect() if r["doc_id"] is not None}
    assert small[0] == small[1] == small[11] == "und" and small[8] == "en"
    assert langid.language_id(empty).count() == 0


def test_kernel_is_presence():
    a, b = "the cat sat", "the hat"
    x = langid.presence([a, b])
    sets = [set(langid.ngram_buckets(t).tolist()) for t in (a, b)]
    assert x[0] @ x[1] == pytest.approx(len(sets[0] & sets[1]) / np.sqrt(len(sets[0]) * len(sets[1])), abs=1e-6)


PAGE = """<!DOCTYPE html><html><head><title>No &amp; no</title><style>p{}</style><script>var t="</p>";</script></head><body class="post">
<header><a href=/>Site</a></header><nav><ul><li><a href="/x">Menu</a></ul></nav><div class="cookie-notice">We use cookies</div>
<main><h1>Head&eacute; <i>l</i>ine</h1><p>One  two<br>three<p>Four <a href="y>z">linked</a> text &amp;amp; &lt;b&gt;<div class="ad">Buy this now, it is a very long advert text indeed and goes on</div>
<table><tr><td>cell</td></tr></table><form><label>Name</label><input></form></main><aside>Side</aside>
<section id="comments"><p>A reader's remark that is rather long and goes on for a while, as they do.</p></section><footer>&copy; me</footer>"""


def test_html(spark):
    assert html_text.main_text(PAGE) == "Headé line One two three Four linked text &amp; <b> cell"
    table = spark.createDataFrame([(1, "u", PAGE, 1), (2, None, None, 2), (3, "v", "", 3), (4, "w", "<p", 4), (4, "w", "plain words", 4)], "page_id long, url string, html string, text int")
    got = sorted((r["page_id"], r["text"], r["n_chars"]) for r in html_text.extract_pages(table).collect())
    assert got[1:] == [(2, "", 0), (3, "", 0), (4, "", 0), (4, "plain words", 11)] and got[0][2] == len(got[0][1])
    assert html_text.extract_pages(table.limit(0)).count() == 0


def test_html_pages(spark):
    import html as lib

    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_text.extract_pages(pages).collect()}
    for r in pages.collect():
        body = re.search(r"<article>(.*?)(</article>|$)", r["html"], re.S)[1]
        want = " ".join(lib.unescape(re.sub(r"</?b>", "", re.sub(r"</?(?:p|h1|br)\b[^>]*>", "\n", body))).split())
        assert got[r["page_id"]] == want


def test_min_cut_is_minimum():
    rng = random.Random(6)
    for _ in range(200):
        n = rng.randrange(1, 9)
        terminals = [(rng.randrange(20), rng.randrange(20)) for _ in range(n)]
        links = {(i, j): rng.randrange(1, 15) for i in range(n) for j in range(i + 1, n) if rng.random() < 0.5}

        def value(side):
            cut = sum(b if s else a for (a, b), s in zip(terminals, side, strict=True))
            return cut + sum(c for (i, j), c in links.items() if side[i] != side[j])

        least = min(value([bool(m >> i & 1) for i in range(n)]) for m in range(1 << n))
        assert value(html_text.min_cut(terminals, links)) == least


def test_training_order(docs, empty, tmp_path):
    from public_tokenizers import PATTERN

    plain = tiktoken.Encoding("plain", pat_str=PATTERN, mergeable_ranks=feistel.read_ranks(), special_tokens={})
    want = {(r[0], r[1] or ""): [*plain.encode_ordinary(r[1] or ""), feistel.END] for r in ROWS}
    ordered = feistel.training_order(docs, sequence=64, shard_sequences=16).cache()
    got = ordered.orderBy("slot").collect()
    assert [r["slot"] for r in got] == list(range(len(got)))
    assert len(got) == sum(-(-len(want[r[0], r[1] or ""]) // 64) for r in ROWS)
    joined = defaultdict(list)
    for r in sorted(got, key=lambda r: r["seq_no"]):
        ids = np.frombuffer(r["record"], "<u2")
        assert r["record_crc32"] == zlib.crc32(r["record"]) and r["shard"] == r["slot"] // 16 and r["shard_offset"] == r["slot"] % 16 * 128
        assert (ids[r["n_tokens"] :] == feistel.PAD).all()
        joined[r["doc_id"]] += ids[: r["n_tokens"]].tolist()
    for doc_id, _, *_ in ROWS:
        same_id = [r[1] or "" for r in ROWS if r[0] == doc_id]
        if len(same_id) == 1:
            assert joined[doc_id] == want[doc_id, same_id[0]] and plain.decode(joined[doc_id][:-1]) == same_id[0]
    feistel.write_shards(feistel.shard_files(docs, sequence=64, shard_sequences=16), str(tmp_path))
    read = feistel.read_sequences(str(tmp_path), 10, 30, 64, 16)
    assert read.tobytes() == b"".join(bytes(r["record"]) for r in got[10:40])
    assert feistel.training_order(empty).count() == 0


def plain_slot(x, n, key, rounds=6):
    """The permutation again, one number at a time."""
    full = (1 << 64) - 1

    def mixed(h):
        h = ((h ^ (h >> 30)) * 0xBF58476D1CE4E5B9) & full
        h = ((h ^ (h >> 27)) * 0x94D049BB133111EB) & full
        return h ^ (h >> 31)

    half = max(1, (max(n - 1, 1).bit_length() + 1) // 2)
    keys = [mixed((i * 0x9E3779B97F4A7C15 + key) & full) for i in range(1, rounds + 1)]
    while True:
        left, right = x >> half, x & ((1 << half) - 1)
        for k in keys:
            left, right = right, left ^ (mixed((right + k) & full) & ((1 << half) - 1))
        x = left << half | right
        if x < n:
            return x


def test_order_does_not_depend_on_splits(spark, tmp_path):
    """Against the plain permutation of the sequences as the files store them, under two split sizes."""
    from public_tokenizers import PATTERN

    plain = tiktoken.Encoding("plain", pat_str=PATTERN, mergeable_ranks=feistel.read_ranks(), special_tokens={})
    RNG.seed(11)
    made = spark.createDataFrame([(i % 40, sentence(RNG.randrange(1, 400)), 1) for i in range(400)], "doc_id long, text string, slot int")
    made.repartition(3).write.option("parquet.block.size", 16384).parquet(f"{tmp_path}/t")
    stored = spark.read.parquet(f"{tmp_path}/t").select("doc_id", "text", "_metadata.file_path", "_metadata.row_index").collect()
    numbered = [(r["doc_id"], n, len(ids[a : a + 64])) for r in sorted(stored, key=lambda r: (r["file_path"], r["row_index"])) for ids in [[*plain.encode_ordinary(r["text"]), 0]] for n, a in enumerate(range(0, len(ids), 64))]
    want = {plain_slot(i, len(numbered), 99): x for i, x in enumerate(numbered)}
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    try:
        for size in ("16k", "1m"):
            spark.conf.set("spark.sql.files.maxPartitionBytes", size)
            read = spark.read.parquet(f"{tmp_path}/t")
            got = feistel.training_order(read, key=99, sequence=64, shard_sequences=32).collect()
            assert {r["slot"]: (r["doc_id"], r["seq_no"], r["n_tokens"]) for r in got} == want and len(got) == len(want)
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)


def test_portions_change_no_id():
    from public_tokenizers import PATTERN

    plain = tiktoken.Encoding("plain", pat_str=PATTERN, mergeable_ranks=feistel.read_ranks(), special_tokens={})
    rng = random.Random(3)
    text = "".join(rng.choice(["word", " ", "  ", "\n", "é", "12", ".", " don't"]) for _ in range(4000))
    tokens = feistel.Tokens(tuple(feistel.read_ranks().items()))
    for t in (text, text.replace("  ", ""), "", " ", "  ", " a", "a ", "a  b", "\n x \ty z\n", "it's  they'll\u00a0x\u2003 y"):
        t = t if t == text else f" {t} x" * 100
        cut = feistel.portions(t, 200)
        assert "".join(cut) == t and [i for p in cut for i in plain.encode_ordinary(p)] == plain.encode_ordinary(t), t
        assert tokens.ids(t).tolist() == [*plain.encode_ordinary(t), feistel.END] and tokens.number(t) == len(tokens.ids(t))
    assert len(feistel.portions(text, 200)) > 20 and max(map(len, feistel.portions("a" * 300_000))) <= 2 * feistel.PORTION
    assert tokens.ids("a" * 300_000)[-1] == feistel.END


@pytest.mark.parametrize("kept", [40, 1 << 19])
def test_words_are_tokenised_once(monkeypatch, kept):
    """Whatever white space, stops and marks a text has its ids are those of the whole; what was seen isn't tokenised again."""
    from public_tokenizers import PATTERN

    monkeypatch.setattr(feistel, "KEPT", kept)
    monkeypatch.setattr(feistel, "SLICE", 5_000)
    plain = tiktoken.Encoding("plain", pat_str=PATTERN, mergeable_ranks=feistel.read_ranks(), special_tokens={})
    tokens = feistel.Tokens(tuple(feistel.read_ranks().items()))
    rng = random.Random(5)
    odd, even = [*"ab1'.,- \n\t\r\xa0\u3000\x1c\x85\x00\u00e9", "'s", " a", "\nA", "c,"], ["ab", " c", "\nd", " e's", ".", ",", "\xa0f", " 12", "\u00e9"]
    texts = ["", " ", "\n", "\nx", " x", "x ", "x\n"] + ["".join(rng.choice(a) for _ in range(rng.randrange(30))) for a in (odd, even) for _ in range(2000)]
    want = [[*plain.encode_ordinary(t), feistel.END] for t in texts]
    assert [i.tolist() for i in tokens.all_ids(pa.array(texts))] == want and tokens.numbers(pa.array(texts)) == [len(w) for w in want]
    assert tokens.numbers(pa.array([], pa.string())) == [] and len(tokens.kept.words) <= max(kept, 5_000)
    if kept > 40:
        words = pa.array(["".join(rng.choice("abc") for _ in range(4)) + " the, same.\nWords again." for _ in range(500)])
        tokens.numbers(words)
        seen = []
        monkeypatch.setattr(tokens, "encoding", type("E", (), {"encode_ordinary": staticmethod(lambda t: seen.append(t) or plain.encode_ordinary(t))}))
        assert sum(len(i) for i in tokens.all_ids(words)) == sum(tokens.numbers(words)) and not "".join(seen)


@pytest.mark.parametrize("part", [7, 1 << 18])
def test_words_are_cut_at_boundaries_only(monkeypatch, part):
    """Letters beyond ASCII, signs, odd white space, zero bytes, words about the length told apart as numbers, and texts of several slices."""
    from public_tokenizers import PATTERN

    monkeypatch.setattr(feistel, "PART", part)
    monkeypatch.setattr(feistel, "SLICE", 500)
    monkeypatch.setattr(feistel, "PORTION", 400)
    plain = tiktoken.Encoding("plain", pat_str=PATTERN, mergeable_ranks=feistel.read_ranks(), special_tokens={})
    tokens = feistel.Tokens(tuple(feistel.read_ranks().items()))
    rng = random.Random(6)
    pool = [*"ab1'.,_(\" \n\t\x00\x1c\x85\xa0\u2003\u3000\u200b\xd7\xf7\xe9\xdf\xc0\u201c\u65e5\U0001f600\xb2", "'s", "  ", "\n\n", "Wort,", "\xe9,", "\xd7."]
    texts = ["", "a", "a\x00", "a\x00\x00", "\x00", "abcdef", "abcdefg", "abcdefgh", "abcdef\x00", "abcdefg\x00", " ", "\n"] + ["".join(rng.choices(pool, k=rng.randrange(40))) for _ in range(600)]
    texts += [" ".join("".join(rng.choices("ab,\xe9\u65e5", k=rng.randrange(1, 9))) for _ in range(2000)), "ab.\n" * 100 + "a" * 450 + " b\n", "no\tspace\n" * 300]
    want = [[*plain.encode_ordinary(t), feistel.END] for t in texts]
    assert [i.tolist() for i in tokens.all_ids(pa.array(texts))] == want
    assert tokens.numbers(pa.array(texts).slice(5)) == [len(w) for w in want[5:]]


def test_words_beside_white_space_and_signs_are_kept():
    """White space that meets or ends a text sends no text back to the tokeniser, and a sign behind a word or a line end before it makes no other word of it."""
    tokens = feistel.Tokens(tuple(feistel.read_ranks().items()))
    seen, encode = [], tokens.encoding.encode_ordinary
    tokens.encoding = type("E", (), {"encode_ordinary": staticmethod(lambda t: seen.append(t) or encode(t))})
    tokens.numbers(pa.array(["One word (two words)\n\n  and  more.  ", "One\tword! "]))
    assert sum(t.count(" word") for t in seen) == 2  # word, words
    seen.clear()
    texts = pa.array(["more word! words) and\n\n  and  more.  ", "One word (two"])
    tokens.numbers(texts)
    assert sum(map(len, seen)) < 20  # " more" and what ends in white space, but no text
    seen.clear()
    assert tokens.numbers(texts) == [len(i) for i in tokens.all_ids(texts)] and not seen


@pytest.mark.parametrize("n", [1, 2, 3, 5, 64, 1000, 4097])
def test_feistel_is_permutation(n):
    slots = feistel.permute(np.arange(n), n, 7)
    assert sorted(slots.tolist()) == list(range(n))
    if n > 100:
        assert (slots != feistel.permute(np.arange(n), n, 8)).mean() > 0.9
        assert abs(np.corrcoef(np.arange(n), slots)[0, 1]) < 0.15


@pytest.mark.parametrize("sizes", [{"en": 300}, {"en": 300, "fr": 40}, {"en": 200, "fr": 200}, {"en": 300, "fr": 60, "de": 40}, {"en": 100, "de": 100, "es": 100}, {"en": 300, "fr": 94, "de": 80, "es": 75}])
def test_unknown_languages_are_rejected(spark, sizes):
    texts = defaultdict(list)
    for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("text RLIKE '[a-z]'").orderBy("doc_id").collect():
        texts[r["lang"]].append(r["text"])
    model = langid.fit([(t[:2000], k) for k, n in sizes.items() for t in texts[k][: min(n, len(texts[k]) - 25)]])

    def kept(some):
        return np.mean(model.accepts(*model.judge(some)))

    rng = random.Random(8)
    noise = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz   ") for _ in range(n)) for n in (200, 2000, 5000) for _ in range(20)]
    other = [" ".join("".join(rng.choice(a) for _ in range(rng.randrange(2, 9))) for _ in range(60)) for a in ("абвгдежзиклмнопрст", "一二三四五六七八九十") for _ in range(20)]
    assert kept(noise) == kept(other) == 0
    for k, own in texts.items():
        long = [t for t in own[-25:] if len(t) > 200]
        assert kept(long) >= 0.9 if k in sizes else kept(long) <= 0.1, k


def test_texts_in_two_known_languages_are_accepted(spark):
    texts = defaultdict(list)
    for r in spark.read.parquet("/root/testdata/sf0.1/documents.parquet").where("length(text) BETWEEN 600 AND 2000 AND doc_id < 4000").orderBy("doc_id").collect():
        texts[r["lang"]].append(r["text"])
    langs = sorted(k for k in texts if k)
    model = langid.fit([(t, k) for k in langs for t in texts[k][:100]])
    shares = [(a, b, n) for a in langs for b in langs if a != b for n in range(8)]
    mixed = [texts[a][-1 - n % len(texts[a])][:600] + "\n" + texts[b][-1 - n % len(texts[b])][:600] for a, b, n in shares]
    values, least = model.judge(mixed)
    by_one = values.max(axis=1) >= least[np.arange(len(mixed)), values.argmax(axis=1)]
    assert by_one.mean() < 0.9 and model.accepts(values, least).mean() >= 0.97


def test_language_stage_drops_noise(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    rng = random.Random(8)
    noise = [(-1 - i, "".join(rng.choice("bcdfghjklmnpqrstvwxz   ") for _ in range(800)), None) for i in range(20)]
    before = docs.where("text RLIKE '[a-z]' AND length(text) > 100").count()
    kept = corpus_pipeline.identify_language(spark, docs.union(spark.createDataFrame(noise, docs.schema)), "").cache()
    assert kept.where("doc_id < 0").count() == 0
    assert kept.where("text RLIKE '[a-z]' AND length(text) > 100").count() >= 0.97 * before


def test_near_copies_are_exact_at_the_threshold(spark):
    rng = random.Random(21)
    texts = []
    for n in (*range(40, 60), 120, 250):
        for changed in (1, 2, 4):
            base = [rng.choice("abcdefgh") + str(rng.randrange(10**6)) for _ in range(n)]
            other = list(base)
            for i in range(changed):
                other[n // 2 + 3 * i] = f"changed{n}x{i}"
            texts += [base, other]
    made = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    classes = {r["doc_id"]: r["class_id"] for r in simhash.near_copies(made).collect()}
    sets = [{tuple(t[i : i + 5]) for i in range(len(t) - 4)} for t in texts]
    share = [len(sets[i] & sets[i + 1]) / len(sets[i] | sets[i + 1]) for i in range(0, len(texts), 2)]
    assert sum(0.75 < s < 0.8 for s in share) >= 5 and sum(0.8 <= s < 0.85 for s in share) >= 5
    assert classes == closure(range(len(texts)), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))


def test_training_order_query_writes_its_shards(spark, docs, empty, tmp_path):
    key = lambda r: r["slot"]
    want = sorted(feistel.training_order(docs, sequence=64, shard_sequences=16).collect(), key=key)
    made = feistel.training_shards(docs, str(tmp_path), sequence=64, shard_sequences=16)
    got = sorted(made.collect(), key=key)
    assert sorted(made.columns) == sorted(want[0].asDict()) and [r["record"] for r in got] == [r["record"] for r in want]
    assert [(r["slot"], r["shard"], r["shard_offset"], r["n_tokens"], r["record_crc32"]) for r in got] == [(r["slot"], r["shard"], r["shard_offset"], r["n_tokens"], r["record_crc32"]) for r in want]
    assert {(r["doc_id"], r["seq_no"]) for r in got} == {(r["doc_id"], r["seq_no"]) for r in want}
    assert feistel.read_sequences(str(tmp_path), 0, 10**6, 64, 16).tobytes() == b"".join(bytes(r["record"]) for r in want)
    file = next((tmp_path / "shards" / "shard=1").glob("part-*"))
    data = bytearray(file.read_bytes())
    data[5 * 128] ^= 1
    file.write_bytes(data)
    for crc in file.parent.glob(".*.crc"):
        crc.unlink()
    changed = {r["slot"] for r in feistel.written_sequences(spark, str(tmp_path), 64, 16).collect() if r["record_crc32"] != want[r["slot"]]["record_crc32"]}
    assert changed == {16 + 5}
    assert feistel.training_shards(empty).count() == 0
    from ldp_hist.llm import shared

    before = set(os.listdir(shared.shared_dir(spark).removeprefix("file://")))
    rows = QUERIES["op1_training_order"](spark, SF).count()
    (new,) = [x for x in set(os.listdir(shared.shared_dir(spark).removeprefix("file://"))) - before if x.startswith("training-order-")]
    assert len(feistel.read_sequences(os.path.join(shared.shared_dir(spark).removeprefix("file://"), new), 0, 10**6)) == rows > 0


@pytest.mark.parametrize("parts", [1, 10])
def test_line_counts_do_not_depend_on_partitions(spark, parts):
    made = spark.createDataFrame([(1, "a line that is long enough\nmine")] * 9 + [(2, "yours\nA line that is long enough")], "doc_id long, text string")
    kept = line_dedup.dedup_lines(made.repartition(parts), min_chars=15, min_docs=10, keep_first=True).where("doc_id = 2").collect()
    assert [r["text"] for r in kept] == ["yours"]

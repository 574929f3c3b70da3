"""The corpus pipeline against brute force, stage by stage and end to end."""

import random
import re
from collections import defaultdict

import numpy as np
import pytest

import corpus_pipeline
from ldp_hist.llm import decontaminate, langid, pieces, words
from tests.llm.test_methods import plain_search

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, row string, row_key string, lang_pred string, item_ids string, kept_text string, gone_key string"


def fold(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


@pytest.fixture(scope="module")
def fixture(spark, tmp_path_factory):
    """Real documents, with copies that repeat id and text, near copies, shared lines, benchmark passages, noise, nulls, and a long text."""
    rng, folder = random.Random(17), str(tmp_path_factory.mktemp("pipeline"))
    taken = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("length(text) > 200").orderBy("doc_id").limit(260).collect()
    rows = [(r["doc_id"], r["text"], r["lang"]) for r in taken]
    first = [r for r in rows if r[2] == "en"][:12]
    rows += [first[0]] * 3 + [(10_001, first[1][1], None), (10_002, first[1][1].upper(), "en")]
    w = first[2][1].split()
    for i in range(3):
        v = list(w)
        v[len(v) // 2 + i] = "other"
        rows.append((10_010 + i, " ".join(v), "en"))
    line = "This very line is shared by ever so many documents"
    rows += [(10_100 + i, f"{line}\n{first[i][1][:300]} {i}\n  {line.upper()} ", "en") for i in range(11)]
    passage = " ".join(f"benchmark{rng.randrange(10**6)} the of" for _ in range(20))
    rows += [(10_200, f"{first[3][1]} {passage} and more", "en"), (10_201, first[4][1] + " " + " ".join(passage.split()[30:] + passage.split()[:30]), "en")]
    rows += [(10_300 + i, "".join(rng.choice("bcdfghjklmnpqrstvwxz   ") for _ in range(700)), None) for i in range(4)]
    rows += [(10_400, None, None), (10_401, "", "en"), (10_402, "123 456", "en"), (None, first[5][1] + " without an id", "en"), (10_403, " ".join(r[1] for r in rows[:200]), "en")]
    full = [(a, t, k, "s", len(t or ""), "row", "row_key", "und", "[]", "kept", None) for a, t, k in rows]
    spark.createDataFrame(full, COLUMNS).repartition(4).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(1, passage), (2, None), (None, "x y z")], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    return folder, passage


def values(df):
    return sorted(((r["doc_id"], r["text"], r["lang"]) for r in df.collect()), key=repr)


def brute_language(model, rows):
    out = []
    for a, t, k in rows:
        if t and any(c.isalpha() for c in t):
            value, least = model.judge([t])
            b = value[0].argmax()
            if value[0, b] > 0 and (value[0, b] >= least[0, b] or value[0].sum() >= least[0, -1]):
                out.append((a, t, k or model.langs[b]))
    return out


def brute_lines(rows):
    strip = lambda x: fold(x.strip(" \t\n\x0b\x0c\r"))
    held, first = defaultdict(int), {}
    for a, t, _ in rows:
        for key in {strip(x) for x in (t or "").split("\n")}:
            held[key] += 1
    due = {k for k, n in held.items() if n >= 10 and len(k) >= 15}
    for a, t, _ in rows:
        for pos, x in enumerate((t or "").split("\n")):
            if strip(x) in due:
                first.setdefault(strip(x), []).append((a is not None, a or 0, pos, t))
    least = {k: min(v, key=lambda x: x[:3]) for k, v in first.items()}
    return [(a, t if t is None else "\n".join(x for pos, x in enumerate(t.split("\n")) if strip(x) not in due or (a is not None, a or 0, pos) == least[strip(x)][:3]), k) for a, t, k in rows]


def brute_copies(rows):
    sets = []
    for _, t, _ in rows:
        w = re.findall(rb"[^\x20\x09-\x0d]+", (t or "").encode().lower())
        k = min(5, len(w))
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else frozenset())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] == sets[j] or (len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) and sets[i]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    classes = defaultdict(list)
    for i in range(len(rows)):
        classes[find(i)].append(i)
    return [min((rows[i] for i in ids), key=lambda r: (r[0] is not None, r[0] or 0)) for ids in classes.values()]


def brute_leaks(rows, passage):
    want = words.shingle_hashes(decontaminate._words(passage), 5)

    def leaks(t):
        have = words.shingle_hashes(decontaminate._words(t), 5)
        return any(decontaminate.weighted_similarity(have[s : s + len(want)], want) >= 0.8 for s in range(len(have)))

    return [r for r in rows if not leaks(r[1])]


def test_run_is_brute_force(spark, fixture):
    folder, passage = fixture
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    rows = [(r["doc_id"], r["text"], r["lang"]) for r in docs.collect()]
    model = langid.train(docs)
    want, stages = rows, (lambda x: brute_language(model, x), brute_lines, brute_copies, lambda x: brute_leaks(x, passage))
    for (name, stage), brute in zip(corpus_pipeline.STAGES, stages):
        before = len(want)
        got = stage(spark, docs, folder)
        assert got.columns == docs.columns
        want = sorted(brute(want), key=repr)
        assert values(got) == want, name
        assert len(want) < before or name == "line dedup"
        assert all(r["kept_text"] == "kept" and r["row_key"] == "row_key" for r in got.collect())
        got.write.mode("overwrite").parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    ids = {r[0] for r in want}
    assert not ids & {10_001, 10_002, 10_010, 10_200, 10_201, 10_300, 10_301, 10_400, 10_401, 10_402} and None in ids
    v = pieces.Vocabulary.load()
    out = {(r["doc_id"], r["lang"]): r for r in corpus_pipeline.run(spark, folder).collect()}
    assert len(out) == len(want)
    for a, t, k in want:
        if len(t) < 5000:
            assert list(out[a, k]["token_ids"]) == plain_search(v, pieces.SPACE + t.replace(" ", pieces.SPACE))
        assert out[a, k]["round_trip"] and out[a, k]["n_tokens"] == len(out[a, k]["token_ids"])


@pytest.mark.parametrize("stage", [f for _, f in corpus_pipeline.STAGES], ids=[n for n, _ in corpus_pipeline.STAGES])
def test_stages_on_edges(spark, fixture, stage):
    folder, _ = fixture
    empty = spark.createDataFrame([], COLUMNS)
    assert stage(spark, empty, folder).count() == 0
    rows = [(None, None, None), (1, "", None), (1, None, "en"), (2, " \n ", "en"), (3, "!!!", "en"), (3, "!!!", "en")]
    odd = spark.createDataFrame([(a, t, k, None, None, None, None, None, None, None, None) for a, t, k in rows], COLUMNS)
    got = stage(spark, odd, folder).collect()
    expected = {"identify_language": 0, "drop_repeated_lines": 6, "drop_near_copies": 2, "drop_contaminated": 6, "encode_pieces": 6}[stage.__name__]
    assert len(got) == expected


def test_one_row_of_a_repeated_row_stays(spark):
    rng = np.random.default_rng(2)
    text = " ".join(f"w{i}" for i in rng.integers(0, 10**6, 50))
    made = spark.createDataFrame([(7, text, "en")] * 9 + [(8, text.upper(), "en"), (9, "another text altogether", "fr")], "doc_id long, text string, lang string").repartition(3)
    got = corpus_pipeline.drop_near_copies(spark, made, "").collect()
    assert sorted(r["doc_id"] for r in got) == [7, 9]

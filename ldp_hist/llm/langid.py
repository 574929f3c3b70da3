"""Language identification with string kernels.

The kernel of two texts counts the character n-grams (1 to 3, the blended spectrum) present in both,
normalised by the square roots of their numbers. Landmark texts give Nyström features, one-versus-rest
kernel ridge regression the weights; as the kernel is a product of presence vectors, landmarks and
weights fold into one matrix, and a batch of texts is scored by one matrix product.

Targets are 1 for a language's own texts and 0 for others, all languages weigh the same and there is no
intercept, so a text that shares no n-gram with the landmarks gets 0 from every language, whatever
their number and shares. How much a language's own texts get depends on their length, so the least
response that a language accepts is calibrated by the number of n-grams, on rows left out of the fit.
A text in several of the languages splits its response among them, so no single one may accept it. The
total over all languages stays near 1 then, and reaching what known texts reach in total is accepted too.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ldp_hist.llm.shared import packed

BUCKETS, NGRAMS, PIECE = 1 << 14, 3, 2000
#: The bound on the training sample: so many rows a language, of all languages together, and characters of
#: each row; and the number of landmarks among them (two a language at least).
SAMPLE_PER_LANG, SAMPLE_ROWS, LANDMARKS, RIDGE = 300, 4800, 256, 1e-2


def ngram_buckets(text: str) -> np.ndarray:
    """Buckets of all n-grams of the lower-cased text, digits and punctuation blanked; with repeats."""
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint32)
    letter = (code >= 0xAA) | ((code >= 97) & (code <= 122))
    code = np.where(letter, code, 32)
    keep = np.ones(len(code), bool)
    keep[1:] = (code[1:] != 32) | (code[:-1] != 32)
    code = code[keep]
    out, h = [], np.zeros(len(code), np.uint32)
    for n in range(NGRAMS):
        if n >= len(code):
            break
        h = (h[: len(code) - n] * np.uint32(0x01000193)) ^ (code[n:] * np.uint32(0x9E3779B1))
        out.append(((h ^ (h >> np.uint32(15))) * np.uint32(0x85EBCA6B)) >> np.uint32(18))
    return np.concatenate(out) if out else np.zeros(0, np.uint32)


def presence(texts: list[str]) -> np.ndarray:
    """One row a text: n-gram presence, scaled so that a row times itself is 1."""
    x = np.zeros((len(texts), BUCKETS), np.float32)
    for row, text in zip(x, texts, strict=True):
        row[ngram_buckets(text)] = 1
    return x / np.sqrt(np.maximum(x.sum(axis=1, keepdims=True), 1))


#: What a language's own texts of a length nearly all reach, and the part of it that is asked for; so many of them make a level of their own.
REJECTED, SLACK, LEVEL_LEAST, LEVELS, CALIBRATED = 0.01, 0.8, 20, 16, 150
#: More than any total: where nothing was calibrated, the total accepts nothing.
UNREACHED = 1e6


def level_of(x: np.ndarray) -> np.ndarray:
    """The power of two of the number of distinct n-grams, from the rows of ``presence``."""
    return np.log2(np.maximum(np.count_nonzero(x, axis=1), 1)).astype(int)


@dataclass
class Model:
    langs: list[str]
    weights: np.ndarray  # buckets x languages
    least: np.ndarray  # levels x languages, then the total

    def judge(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """By language the mean response to each text's pieces of ``PIECE`` characters, and the mean that it (in one more column, the total) has to reach."""
        pieces = [(i, t[a : a + PIECE]) for i, t in enumerate(texts) for a in range(0, max(len(t), 1), PIECE)]
        total, least, count = np.zeros((len(texts), len(self.langs))), np.zeros((len(texts), len(self.langs) + 1)), np.zeros((len(texts), 1))
        for at in range(0, len(pieces), 256):
            part = pieces[at : at + 256]
            owner, size = np.array([i for i, _ in part]), np.array([[len(t)] for _, t in part])
            x = presence([t for _, t in part])
            np.add.at(total, owner, (x @ self.weights) * size)
            np.add.at(least, owner, self.least[level_of(x)] * size)
            np.add.at(count, owner, size)
        return total / np.maximum(count, 1), least / np.maximum(count, 1)

    @staticmethod
    def accepts(values: np.ndarray, least: np.ndarray) -> np.ndarray:
        """Which rows of ``judge`` are accepted: by the language that responds most, or by all of them in total."""
        i, best = np.arange(len(values)), values.argmax(axis=1)
        return (values[i, best] > 0) & ((values[i, best] >= least[i, best]) | (values.sum(axis=1) >= least[:, -1]))

    def score(self, texts: list[str]) -> np.ndarray:
        return self.judge(texts)[0]


def _weights(x: np.ndarray, lang: np.ndarray, classes: int) -> np.ndarray:
    """Kernel ridge regression on Nyström features; landmarks are taken from the languages in turn."""
    by_lang = [np.flatnonzero(lang == k) for k in range(classes)]
    turn = [ids[n] for n in range(max(map(len, by_lang))) for ids in by_lang if n < len(ids)]
    marks = x[turn[: max(LANDMARKS, 2 * classes)]]
    value, vector = np.linalg.eigh((marks @ marks.T).astype(np.float64))
    root = vector / np.sqrt(np.maximum(value, 1e-6))  # K^(-1/2) up to rotation
    features = (x @ marks.T) @ root
    sizes = np.array([len(ids) for ids in by_lang])
    weighted = features * (len(x) / (np.count_nonzero(sizes) * sizes[lang]))[:, None]
    solved = np.linalg.solve(weighted.T @ features + RIDGE * len(x) * np.eye(len(marks)) / 10, weighted.T @ np.eye(classes)[lang])
    return (marks.T.astype(np.float64) @ (root @ solved)).astype(np.float32)


def _by_level(level: np.ndarray, value: np.ndarray, slack: float) -> np.ndarray:
    """``slack`` of the ``REJECTED`` quantile of each level, never less than at the one below it; a level of too few values takes that one's."""
    out = np.full(LEVELS, np.nan)
    for b in range(LEVELS):
        here, below = value[level == b], out[b - 1] if b else np.nan
        out[b] = np.fmax(slack * np.quantile(here, REJECTED), below) if len(here) >= LEVEL_LEAST else below
    return out


def _least(texts: list[str], lang: np.ndarray, nth: np.ndarray, x: np.ndarray, classes: int) -> np.ndarray:
    """The least accepted response by level and language, and in the last column the least accepted total.

    Every other row of a language is left out of the fit that answers it, whole and cut to all powers of two
    of its length. Levels are filled from the short end; one of too few answers takes the level below it, none asks for less than that one
    (more n-grams say more, unless they are junk with a label), and a language with a single row takes the least of the others. What a language
    accepts begins at ``SLACK`` of the ``REJECTED`` quantile of its own texts, for texts of it that the sample does not show. The total has no
    such slack: junk shares letters with every language, and the total adds that up.
    """
    answers: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
    for fold in (0, 1):
        used = nth % 2 != fold
        if not used.any():
            continue
        weights = _weights(x[used], lang[used], classes)
        held = [i for i in np.flatnonzero(~used & (nth < CALIBRATED)) if (used & (lang == lang[i])).any()]
        cuts = [(lang[i], texts[i][at : at + n]) for i in held for n in {*(1 << b for b in range(2, 11)), PIECE} for at in [max(0, len(texts[i]) - n) // 2] if n <= len(texts[i]) or n == PIECE]
        for at in range(0, len(cuts), 256):
            own = np.array([k for k, _ in cuts[at : at + 256]])
            seen = presence([t for _, t in cuts[at : at + 256]])
            response = seen @ weights
            answers.append((level_of(seen), own, response[np.arange(len(own)), own], response.sum(axis=1)))
    if not answers:
        return np.append(np.zeros((LEVELS, classes)), np.full((LEVELS, 1), UNREACHED), axis=1)
    level, own, value, total = (np.concatenate(a) for a in zip(*answers, strict=True))
    out = np.stack([_by_level(level[own == k], value[own == k], SLACK) for k in range(classes)], axis=1)
    few = np.isnan(out).all(axis=0)
    out[:, few] = np.nanmin(np.where(few, np.nan, out), axis=1, initial=np.inf, keepdims=True) if not few.all() else 0
    whole = np.nan_to_num(_by_level(level, total, 1.0), nan=UNREACHED)
    return np.append(np.maximum(np.where(np.isfinite(out), out, 0), 0), whole[:, None], axis=1)


def fit(rows: list[tuple[str, str]]) -> Model:
    """Fits (text, lang) rows: kernel ridge regression, one language against the rest, and what each accepts."""
    langs = sorted({lang for _, lang in rows})
    texts, x, lang = [t for t, _ in rows], presence([t for t, _ in rows]), np.array([langs.index(k) for _, k in rows])
    nth = np.array([np.count_nonzero(lang[:i] == k) for i, k in enumerate(lang)])
    return Model(langs, _weights(x, lang, len(langs)), _least(texts, lang, nth, x, len(langs)))


def train(docs: DataFrame) -> Model | None:
    """Fits on a bounded sample of labelled rows that are not held out; None if there is none.

    Every language of the table is learned. Counts by language (a scan of ids and languages) set the share of its rows
    whose hash lets them through, one scan of the texts takes them, and of these at most ``SAMPLE_PER_LANG`` rows a language stay,
    fewer if there are so many languages that ``SAMPLE_ROWS`` would be passed (one at least). Rows that
    repeat count once, texts without a letter teach nothing, and of a long text a piece of ``PIECE`` characters from
    a place that the hash names is learned.
    """
    spark, fold = docs.sparkSession, F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3
    known = docs.where(F.col("lang").isNotNull() & (fold != 1))
    counts = {r[0]: r[1] for r in known.groupBy("lang").count().collect()}
    if not counts:
        return None
    each = max(1, min(SAMPLE_PER_LANG, SAMPLE_ROWS // len(counts)))
    share = spark.createDataFrame([(k, min(1.0, 8 * each / n)) for k, n in counts.items()], "lang string, share double")
    order = F.xxhash64(F.lit("sample"), "doc_id")
    drawn = known.select("doc_id", "lang", "text", order.alias("o")).join(F.broadcast(share), "lang").where(F.col("o") / float(1 << 64) + 0.5 <= F.col("share"))
    spare = F.greatest(F.char_length("text") - PIECE, F.lit(0)) + 1
    piece = F.substring("text", (F.pmod(F.xxhash64(F.lit("piece"), "doc_id"), spare) + 1).cast("int"), F.lit(PIECE))
    pieces = drawn.where(F.col("text").rlike(r"\p{L}")).select("lang", "o", "doc_id", piece.alias("t")).distinct()
    nth = F.row_number().over(Window.partitionBy("lang").orderBy("o", "doc_id", "t"))
    rows = pieces.withColumn("nth", nth).where(F.col("nth") <= each).collect()
    return fit([(r["t"], r["lang"]) for r in sorted(rows, key=lambda r: (r["lang"], r["nth"]))]) if rows else None


def _predict(model: Model | None, pick: list[str], text_of):
    """``text_of`` gives a batch's texts, so that a text which is part of a carried row is not sent twice."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                texts, lettered = text_of(part).to_pylist(), part.column("ok").to_pylist()
                pred, score, accepted = ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), bool)
                rows = [i for i, ok in enumerate(lettered) if ok]
                if rows and model:
                    values, least = model.judge([texts[i] for i in rows])
                    for i, b, v, ok in zip(rows, values.argmax(axis=1), values, model.accepts(values, least), strict=True):
                        pred[i], score[i], accepted[i] = model.langs[b], min(1.0, max(0.0, v[b])), ok
                yield pa.record_batch([*part.columns[: len(pick)], pa.array(pred), pa.array(score), pa.array(accepted)], names=[*pick, "lang_pred", "score", "accepted"])

    return run


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """``doc_id`` and ``text_hash`` (null-safe identity of a row) with lang_pred, score and accepted of the whole text.

    The score is the language's response, cut to 0..1. ``und`` with score 0, not accepted, for a null text, one without a letter, and if nothing could be learned.
    Equal responses fall to the language first in alphabetical order.
    """
    lettered = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"), "text", lettered.alias("ok"))
    return read.mapInArrow(_predict(model, ["doc_id", "text_hash"], lambda b: b.column("text")), "doc_id long, text_hash long, lang_pred string, score double, accepted boolean")


def annotate(docs: DataFrame, model: Model | None) -> DataFrame:
    """``row`` (all columns of ``docs``) with lang_pred, score and accepted of the whole text."""
    rows = packed(docs)
    read = rows.select("row", F.coalesce(F.col("row.text").rlike(r"\p{L}"), F.lit(False)).alias("ok"))
    schema = T.StructType(list(rows.schema.fields)).add("lang_pred", "string").add("score", "double").add("accepted", "boolean")
    return read.mapInArrow(_predict(model, ["row"], lambda b: b.column("row").field("text")), schema)


def language_id(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row; trains on the same table's rows that aren't held out.

    A null id is never trained on and counts as not held out. Repeated rows get equal answers. Extra columns
    are ignored, an empty table gives an empty result.
    """
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3
    return predict(docs, train(docs)).select("doc_id", F.coalesce(fold == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")

"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Weights are learned by follow-the-regularised-leader with elastic-net penalties
and the logits are calibrated by one temperature. N-grams of 1 to ``N`` lowered
letters (anything else is a word edge) are hashed into ``DIMENSIONS`` features.

What covers all data: document frequencies, over every training document, whole
texts; predictions, over every row, whole texts. What is bounded: the weights are
fitted on at most about ``SAMPLE`` training documents of each language, chosen by
the smallest hashes of doc_id and text, and held by the driver as sparse rows.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracelake.llm import common, textvec
from tracelake.llm.textvec import U

N = 3
DIMENSIONS = 2**16
SAMPLE = 1500
#: Every language that occurs is learned; a model of more weights than this (4,096 languages) raises.
MOST_WEIGHTS = 2**28
UNKNOWN = "und"
_EDGE = 0
_SPREAD = np.random.default_rng(11).integers(0, 2**63, (N, 2**16), dtype=U) * U(2) + U(1)


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Lowered code point of every letter, 0 of anything else."""
    out = np.zeros(0x110000, dtype=np.uint32)
    for c in range(0x110000):
        sign = chr(c)
        if sign.isalpha():
            low = sign.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


def features(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature numbers of all n-grams of all texts in text order, offsets per text, number of letters per text."""
    tail = "\n" * (N - 1)
    joined = "".join([f"\n{t}{tail}" for t in texts])
    sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts)) + N
    points = _letters()[np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    starts = np.concatenate([[0], np.cumsum(sizes)])
    letter = points != _EDGE
    count = np.add.reduceat(letter, starts[:-1], dtype=np.int64)
    keep = letter.copy()
    keep[1:] |= letter[:-1]  # of several edges in a row, one
    begins = np.ones(len(points), dtype=bool)  # n-grams begin anywhere but in the tail
    for k in range(1, N):
        keep[starts[1:] - k] = True
        begins[starts[1:] - k] = False
    keep[starts[:-1]] = True
    begins = begins[keep]
    position = np.concatenate([[0], np.cumsum(begins)])[np.concatenate([[0], np.cumsum(keep)])[starts]]
    kept = points[keep].astype(U)
    low = (kept & U(0xFFFF)).astype(np.int64)
    high = (kept >> U(16)) * U(0xC2B2AE3D27D4EB4F)
    out = np.zeros((len(kept), N), dtype=np.uint32)
    total = np.zeros(len(kept), dtype=U)
    shift = U(64 - (DIMENSIONS - 1).bit_length())
    for n in range(N):
        part = _SPREAD[n][low[n:]] + high[n:]
        total[: len(part)] += part
        out[:, n] = ((total * U(0x9E3779B97F4A7C15)) >> shift).astype(np.uint32)
    return out[begins].ravel(), position * N, count


def _columns(batch: pa.RecordBatch, name: str = "text"):
    """Slices of a batch's texts: first row, features, offsets, letters."""
    column = batch.column(name)
    sizes = pc.utf8_length(column).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    for a, b in textvec.slices(sizes, 500_000):
        yield a, b, *features([t or "" for t in column.slice(a, b - a).to_pylist()])


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """In how many texts each feature occurs, over all rows, and the number of texts.

    Each task gives at most ``DIMENSIONS`` sums, so the result is bounded.
    """

    def count(batches):
        df, rows = np.zeros(DIMENSIONS, dtype=np.int64), 0
        for batch in batches:
            for a, b, found, offsets, _ in _columns(batch):
                rows += b - a
                text = np.repeat(np.arange(b - a, dtype=np.int64), np.diff(offsets))
                if b - a <= 512:
                    flags = np.zeros((b - a) * DIMENSIONS, dtype=bool)
                    flags[text * DIMENSIONS + found] = True
                    df += flags.reshape(b - a, DIMENSIONS).sum(axis=0)
                else:
                    df += np.bincount(np.unique(text * DIMENSIONS + found) % DIMENSIONS, minlength=DIMENSIONS)
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(df[at], rows))], names=["feature", "df"])

    sums = docs.select("text").mapInArrow(count, "feature bigint, df bigint").groupBy("feature").agg(F.sum("df").alias("df"))
    out, rows = np.zeros(DIMENSIONS, dtype=np.int64), 0
    for r in sums.toLocalIterator():
        if r["feature"] < 0:
            rows = r["df"]
        else:
            out[r["feature"]] = r["df"]
    return out, rows


@dataclass
class Model:
    languages: list[str]
    weights: np.ndarray  # (DIMENSIONS, languages), with the inverse document frequencies in them
    bias: np.ndarray
    temperature: float

    def logits(self, found: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        sizes = np.diff(offsets)
        out = np.zeros((len(sizes), len(self.languages)))
        full = sizes > 0
        if full.any():
            for c in range(len(self.languages)):
                out[full, c] = np.add.reduceat(self.weights[:, c][found], offsets[:-1][full])
            out[full] /= sizes[full, None]
        return out + self.bias

    def probabilities(self, found: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        return softmax(self.logits(found, offsets) / self.temperature)


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def ftrl(rows, labels, classes: int, alpha=0.5, beta=1.0, l1=1e-4, l2=1e-4, passes: int = 4, seed: int = 1):
    """Follow the regularised leader, per coordinate, on sparse rows [(indices, values)].

    Keeps for every weight the adjusted gradient sum z and the squared sum n;
    the weight is 0 while abs(z) <= l1, else it follows from z, n, l1 and l2.
    """
    z = np.zeros((DIMENSIONS + 1, classes))
    n = np.zeros((DIMENSIONS + 1, classes))

    def weights(at):
        zz, nn = z[at], n[at]
        return np.where(np.abs(zz) <= l1, 0.0, -(zz - np.sign(zz) * l1) / ((beta + np.sqrt(nn)) / alpha + l2))

    rng = np.random.default_rng(seed)
    for _ in range(passes):
        for k in rng.permutation(len(rows)).tolist():
            at, x = rows[k]
            w = weights(at)
            p = softmax(x @ w)
            p[labels[k]] -= 1.0
            g = x[:, None] * p
            nn = n[at]
            grown = nn + g * g
            z[at] += g - (np.sqrt(grown) - np.sqrt(nn)) / alpha * w
            n[at] = grown
    return weights(slice(None))


def calibrate(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature with the smallest log loss, by golden-section search on its logarithm."""
    if not len(labels):
        return 1.0
    at = np.arange(len(labels))

    def loss(t: float) -> float:
        return float(-np.log(np.maximum(softmax(logits / np.exp(t))[at, labels], 1e-12)).mean())

    a, b, g = -4.0, 4.0, (5**0.5 - 1) / 2
    for _ in range(50):
        c, d = b - g * (b - a), a + g * (b - a)
        a, b = (a, d) if loss(c) <= loss(d) else (c, b)
    return float(np.exp((a + b) / 2))


def train(docs: DataFrame, sample: int = SAMPLE) -> Model:
    """Learns from the text and the language of ``docs`` (columns doc_id, text, lang; null lang is left out)."""
    common.small_batches(docs.sparkSession)
    docs = docs.where("lang is not null")
    most = MOST_WEIGHTS // DIMENSIONS
    sizes = {r["lang"]: r["count"] for r in docs.groupBy("lang").count().limit(most + 1).collect()}
    if len(sizes) > most:
        raise ValueError(f"more than {most} different values of lang: none is left out silently; clean the labels or raise MOST_WEIGHTS")
    languages = sorted(sizes)
    if not languages:
        return Model([], np.zeros((DIMENSIONS, 0)), np.zeros(0), 1.0)
    df, total = document_frequencies(docs)
    idf = np.log((1.0 + total) / (1.0 + df)) + 1.0
    draw = F.shiftrightunsigned(F.xxhash64("doc_id", "text"), 33) / F.lit(float(2**31))
    shares = docs.sparkSession.createDataFrame([(lang, min(1.0, sample / sizes[lang])) for lang in languages], "s_lang string, share double")
    chosen = docs.withColumn("draw", draw).join(F.broadcast(shares), F.col("lang") == F.col("s_lang"))
    chosen = chosen.where("draw < share").select("lang", "text", "draw")

    def vectors(batches):
        for batch in batches:
            lang, draws = batch.column("lang"), batch.column("draw")
            for a, b, found, offsets, _ in _columns(batch):
                lists, counts = [], []
                for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
                    at, many = np.unique(found[x:y], return_counts=True)
                    lists.append(at.astype(np.int32))
                    counts.append(many.astype(np.float32) / max(y - x, 1))
                yield pa.RecordBatch.from_arrays(
                    [lang.slice(a, b - a), draws.slice(a, b - a), pa.array(lists, pa.list_(pa.int32())), pa.array(counts, pa.list_(pa.float32()))],
                    names=["lang", "draw", "at", "tf"],
                )

    held = chosen.mapInArrow(vectors, "lang string, draw double, at array<int>, tf array<float>").toArrow()
    rows, labels, test = [], [], []
    scale = 40.0
    order = np.argsort(held.column("draw").to_numpy(), kind="stable")
    langs, ats, tfs = (held.column(c).combine_chunks() for c in ("lang", "at", "tf"))
    for place, k in enumerate(order.tolist()):
        at = ats[k].values.to_numpy(zero_copy_only=False).astype(np.int64)
        x = tfs[k].values.to_numpy(zero_copy_only=False).astype(np.float64) * idf[at] * scale
        rows.append((np.append(at, DIMENSIONS), np.append(x, 1.0)))
        labels.append(languages.index(langs[k].as_py()))
        test.append(place % 5 == 4)
    fit = [k for k, t in enumerate(test) if not t]
    w = ftrl([rows[k] for k in fit], [labels[k] for k in fit], len(languages))
    held_out = [k for k, t in enumerate(test) if t]
    logits = np.array([rows[k][1] @ w[rows[k][0]] for k in held_out]).reshape(-1, len(languages))
    temperature = calibrate(logits, np.array([labels[k] for k in held_out], dtype=np.int64))
    return Model(languages, (w[:-1] * idf[:, None] * scale).astype(np.float32), w[-1], temperature)


def held_out(doc_id: Column) -> Column:
    """Whether a document is kept from learning: crc32 of its id as text leaves 1 when divided by 3."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def predict(docs: DataFrame, model: Model, lang_name: str = "lang_pred", score_name: str = "score") -> DataFrame:
    """``docs`` with the predicted language and its score, from whole texts.

    A text that is null or has no letter, and every text if nothing was learned,
    gets ``und`` and score 0.
    """
    common.small_batches(docs.sparkSession)
    names = docs.columns
    text = docs.columns.index("text")

    def label(batches):
        for batch in batches:
            lang, score = [], []
            table = pa.RecordBatch.from_arrays([batch.column(text)], names=["text"])
            for a, b, found, offsets, letters in _columns(table):
                if model.languages:
                    p = model.probabilities(found, offsets)
                    best = p.argmax(axis=1)
                    known = letters > 0
                    lang += [model.languages[k] if ok else UNKNOWN for k, ok in zip(best.tolist(), known.tolist())]
                    score.append(np.where(known, p[np.arange(b - a), best], 0.0))
                else:
                    lang += [UNKNOWN] * (b - a)
                    score.append(np.zeros(b - a))
            added = [pa.array(lang, pa.string()), pa.array(np.concatenate(score) if score else np.zeros(0), pa.float64())]
            yield pa.RecordBatch.from_arrays([*batch.columns, *added], names=[*names, lang_name, score_name])

    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(label, f"{kept}, `{lang_name}` string, `{score_name}` double")


def identify(docs: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """Per row: doc_id, held_out, lang_pred, score. Learns from the rows that are not held out.

    Reads doc_id, text and lang; lang takes part in learning only. A null
    doc_id is not held out. Rows that repeat each other are all predicted alike;
    an empty table gives an empty result.
    """
    learned = train(docs.where(~held_out(F.col("doc_id"))).select("doc_id", "text", "lang"), sample)
    out = predict(docs.select("doc_id", "text"), learned)
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def accepted(docs: DataFrame, least: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """The rows of ``docs`` whose language is recognised with a score of at least ``least``; columns as they were.

    Needs doc_id, text and lang; columns that have the helpers' names stay as they are. A
    text that is null, empty or without a letter is not recognised; without any lang to
    learn from no row is. Rows that repeat each other are judged alike. An empty
    table gives an empty result.
    """
    learned = train(docs.where(~held_out(F.col("doc_id"))).select("doc_id", "text", "lang"), sample)
    p_lang, p_score = common.fresh(docs, "p_lang", "p_score")
    found = predict(docs, learned, p_lang, p_score)
    return found.where((F.col(p_lang) != UNKNOWN) & (F.col(p_score) >= least)).select(*docs.columns)

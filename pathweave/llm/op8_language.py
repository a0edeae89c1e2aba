"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Features are 1- to 3-grams of letters (anything else is one blank), hashed into BUCKETS. Document frequencies come from
all documents that may be learnt from; the classifier is fitted with follow-the-regularised-leader and elastic-net
penalties on a bounded sample of them (about SAMPLE_DOCS, picked by hash, never twice as many), and its temperature is calibrated on a part of
the sample that the fit did not see. Prediction reads whole texts.

Defined cases: null text, or text without a letter, is "und" with score 0; a null language is never learnt from; with
nothing to learn from everything is "und"; repeated rows stay rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BUCKETS, ORDERS, SAMPLE_DOCS, EPOCHS = 1 << 13, (1, 2, 3), 2500, 3
ALPHA, BETA, L1, L2 = 0.5, 1.0, 0.02, 0.1
_ROWS, _CHARS = 128, 1 << 19
_LETTER: np.ndarray | None = None


def _letters() -> np.ndarray:
    global _LETTER
    if _LETTER is None:
        _LETTER = np.array([chr(c).isalpha() for c in range(0x110000)])
    return _LETTER


def counts(texts: list[str]) -> np.ndarray:
    """n-gram counts of each text, one row of BUCKETS for each."""
    x = np.frombuffer("\0".join(t.replace("\0", " ").lower() for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    row = np.cumsum(x == 0)
    letter = _letters()[x]
    keep = letter.copy()
    keep[1:] |= letter[:-1]  # the first of a run of other characters
    keep[:1] = True
    x, row, letter = np.where(letter, x, 32)[keep], row[keep], letter[keep]
    out = np.zeros(len(texts) * BUCKETS, np.int64)
    h = np.zeros(len(x), np.int64)
    for n in range(1, max(ORDERS) + 1):
        h = (h[: len(x) - n + 1] * 1000003 + x[n - 1 :]) & 0xFFFFFFFFFFFF if len(x) >= n else h[:0]
        if n not in ORDERS or not len(h):
            continue
        start, end = row[: len(h)], row[n - 1 :]
        some = letter[: len(h)].copy()
        for i in range(1, n):
            some |= letter[i : i + len(h)]
        ok = (start == end) & some
        bucket = (((h * n + n) * 0x9E3779B1) >> 15) % BUCKETS
        out += np.bincount(start[ok] * BUCKETS + bucket[ok], minlength=len(out))
    return out.reshape(len(texts), BUCKETS)


def groups(texts: list[str | None], most: int = _ROWS) -> Iterator[tuple[int, list[str]]]:
    """Runs of texts of bounded number and size, and where they begin."""
    i = 0
    while i < len(texts):
        j, size = i, 0
        while j < len(texts) and j - i < most and (j == i or size + len(texts[j] or "") <= _CHARS):
            size += len(texts[j] or "")
            j += 1
        yield i, [t or "" for t in texts[i:j]]
        i = j


def parts_of(col: pa.Array, rows: int = 512) -> Iterator[list]:
    """A column's texts a few at a time, so that a batch is never held twice."""
    for i in range(0, len(col), rows):
        yield col.slice(i, rows).to_pylist()


def weighed(c: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """TF-IDF rows of unit length (zero rows stay zero)."""
    v = np.log1p(c).astype(np.float32) * idf
    return v / np.maximum(np.sqrt((v * v).sum(1, keepdims=True)), 1e-12)


def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents of a partition that hold each bucket; bucket BUCKETS counts the documents."""
    df = np.zeros(BUCKETS + 1, np.int64)
    for batch in batches:
        for texts in parts_of(batch.column(0)):
            for _, part in groups(texts):
                df[:BUCKETS] += (counts(part) > 0).sum(0)
        df[BUCKETS] += batch.num_rows
    if df[BUCKETS]:
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(BUCKETS + 1), pa.int32()), pa.array(df)], ["bucket", "df"])


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def fit(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, classes: int, epochs: int = EPOCHS, seed: int = 13) -> np.ndarray:
    """Follow-the-regularised-leader, coordinate by coordinate, over rows of (bucket, value); weights are zero where the L1
    penalty holds them."""
    z, n = np.zeros((classes, BUCKETS)), np.zeros((classes, BUCKETS))
    rnd = np.random.default_rng(seed)

    def weights(z, n):
        return np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))

    for _ in range(epochs):
        for k in rnd.permutation(len(y)):
            i, v = rows[k]
            zi, ni = z[:, i], n[:, i]
            w = weights(zi, ni)
            p = _softmax(w @ v)
            p[y[k]] -= 1
            g = p[:, None] * v[None, :]
            sq = g * g
            z[:, i] = zi + g - (np.sqrt(ni + sq) - np.sqrt(ni)) / ALPHA * w
            n[:, i] = ni + sq
    return weights(z, n).astype(np.float32)


def temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The divisor of logits with the least log loss, by golden section on its logarithm."""
    loss = lambda t: -np.log(np.maximum(_softmax(logits / np.exp(t))[np.arange(len(y)), y], 1e-12)).mean()
    lo, hi, g = -1.0, 3.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = hi - g * (hi - lo), lo + g * (hi - lo)
        lo, hi = (lo, b) if loss(a) < loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


def train(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> dict | None:
    """docs(doc_id, text, lang) that may be learnt from -> classes, weights, idf, temperature."""
    docs = docs.filter("text is not null and lang is not null")
    df = np.zeros(BUCKETS + 1, np.int64)
    for r in docs.select("text").mapInArrow(frequencies, "bucket int, df long").groupBy("bucket").agg(F.sum("df").alias("df")).collect():
        df[r["bucket"]] = r["df"]
    if not df[BUCKETS]:
        return None
    idf = (np.log((1 + df[BUCKETS]) / (1 + df[:BUCKETS])) + 1).astype(np.float32)
    # Rows whose hash falls below a share of its range: about sample_docs of them, never more than twice as many.
    share = min(1.0, sample_docs / int(df[BUCKETS]))
    place = F.shiftrightunsigned(F.xxhash64(F.lit("language"), "doc_id", "text"), 11)  # 53 bits
    some = docs.filter(place < int(share * 2**53) + (share == 1.0)).select("text", "lang").limit(2 * sample_docs).collect()
    some.sort(key=lambda r: (r["lang"], r["text"]))
    if not some:
        return None
    classes = sorted({r["lang"] for r in some})
    rows = []  # (bucket, value) of each text: a few thousand pairs, not a dense row
    for _, part in groups([r["text"] for r in some], 32):
        for v in weighed(counts(part), idf):
            at = np.flatnonzero(v)
            rows.append((at, v[at]))
    y = np.array([classes.index(r["lang"]) for r in some])
    held = np.random.default_rng(7).permutation(len(y)) % 5 == 4
    if held.sum() < 20:
        held[:] = False
    w = fit([r for r, h in zip(rows, held) if not h], y[~held], len(classes))
    logits = np.array([w[:, i] @ v for (i, v), h in zip(rows, held) if h]).reshape(-1, len(classes))
    return {"classes": classes, "weights": w, "idf": idf, "temperature": temperature(logits, y[held]) if held.any() else 1.0}


def predictor(sent):
    """mapInArrow function: doc_id, text -> doc_id, lang_pred, score."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for batch in batches:
            lang, score = [], []
            for part in (p for texts in parts_of(batch.column(1)) for _, p in groups(texts)):
                if m is None:
                    lang += ["und"] * len(part)
                    score += [0.0] * len(part)
                    continue
                c = counts(part)
                p = _softmax((weighed(c, m["idf"]) @ m["weights"].T / m["temperature"]).astype(np.float64))
                some, best = c.any(axis=1), p.argmax(1)
                lang += [m["classes"][b] if s else "und" for b, s in zip(best, some)]
                score += [float(v) if s else 0.0 for v, s in zip(p.max(1), some)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    return run


def accepted(docs: DataFrame, model: dict | None, least_score: float) -> DataFrame:
    """The rows of docs, whole, whose text has a language with at least that score."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = predictor(sent)
        for batch in batches:
            at = [batch.schema.get_field_index(c) for c in ("doc_id", "text")]
            found = next(predict(iter([pa.RecordBatch.from_arrays([batch.column(i) for i in at], ["doc_id", "text"])])))
            keep = [lang != "und" and score >= least_score for lang, score in zip(found.column(1).to_pylist(), found.column(2).to_pylist())]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def learnable(docs: DataFrame) -> DataFrame:
    """Rows that may be learnt from: the checksum of the id as text is not 1 modulo 3."""
    return docs.filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 != 1)


def identify(docs: DataFrame, model: dict | None) -> DataFrame:
    """docs(doc_id, text) -> doc_id, lang_pred, score; one row for each row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(predictor(sent), f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang_pred string, score double")


def languages(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text, lang) -> doc_id, held_out, lang_pred, score."""
    out = identify(docs, train(learnable(docs)))
    return out.withColumn("held_out", F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))).select("doc_id", "held_out", "lang_pred", "score")

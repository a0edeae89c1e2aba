"""Repeated passages by paragraph MinHash banding.

A text's paragraphs are its lines of MIN_WORDS words or more; consecutive shorter lines, up to a blank one, are joined to
one paragraph. As a passage may be pasted into the middle of a line, there are also windows of WINDOW words whose
starts are chosen by content alone: a window starts at every smallest three-word hash among NEAR consecutive ones. A passage
of NEAR + 2 + WINDOW words or more (50) holds at least one whole window, wherever it stands.

Paragraphs are banded on the MinHash of their five-word shingles (bands of two, tuned for recall: a pair of similarity 0.8
is missed with probability 3e-4), colliding ones are confirmed by exact Jaccard on full sets and clustered by components.
Windows are short and must be equal: their cluster is that of equal content. A cluster in two documents or more is a
repeat; its occurrence with the smallest (document, start) is kept, the others are removed. Touching windows that repeat
the same text at the same distance are one span, which is extended word by word to both sides to where it and the kept
occurrence stop agreeing; the kept occurrence is extended likewise. Where texts agree for more than NEAR - 1 words beyond a
window, another window is shared, so no extension looks further than NEAR words. A word that stands in a
removed piece goes, whatever else holds it; pieces are cut at each other's borders and merged into passages of one verdict
and one first document (the smallest of the pieces that gave the verdict).

Defined cases: null and empty texts have no paragraphs; repeated rows (and documents with the same id) are one document,
so they do not repeat each other; a null doc_id takes no part; an empty table gives no rows; other columns are ignored.

Limits: a paragraph of fewer than MIN_WORDS words takes no part; a near copy (not an exact one) of a passage that is pasted
into longer lines is found as far as its equal runs reach, 28 words at least and surely from 50 on.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathweave.llm import common as C
from pathweave.llm import op3_minhash

MIN_WORDS, WINDOW, NEAR, GRAM = 28, 28, 20, 3
SHINGLE, BAND, BANDS, PERCENT = 5, 2, 8, 80
PIECE = ["doc_id", "key", "line", "print", "w0", "w1", "n", "bands"]
_P = np.uint64(0xD6E8FEB86659FD93)
_INV = np.uint64(pow(0xD6E8FEB86659FD93, -1, 1 << 64))


def _pow(base: np.uint64, n: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    if n > 1:
        np.multiply.accumulate(np.full(n - 1, base, np.uint64), out=out[1:])
    return out


def anchors(w: C.Words) -> np.ndarray:
    """Word numbers where content-chosen windows start: leftmost smallest GRAM-hash of each NEAR consecutive ones."""
    g = C.roll(w.hash, GRAM)
    n = len(g) - NEAR + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    val, idx, width = g, np.arange(len(g)), 1
    while width < NEAR:
        step = min(width, NEAR - width)
        a, b = val[: len(val) - step], val[step:]
        left = a <= b
        val, idx = np.where(left, a, b), np.where(left, idx[: len(a)], idx[step:])
        width += step
    whole = w.row[:n] == w.row[NEAR + GRAM - 2 : NEAR + GRAM - 2 + n]
    return np.unique(idx[whole])


def paragraphs(s: np.ndarray, e: np.ndarray, line: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First words and ends of the paragraphs, from those of the lines that have words."""
    long = e - s >= MIN_WORDS
    new = np.ones(len(s), bool)
    new[1:] = long[1:] | long[:-1] | (row[s[1:]] != row[s[:-1]]) | (line[s[1:]] > line[s[:-1]] + 1)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(s)) - 1
    p, q = s[first], e[last]
    return p[q - p >= MIN_WORDS], q[q - p >= MIN_WORDS]


def cutter():
    """mapInArrow function: doc_id, key, text -> paragraphs, and windows with their first word only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rnd = np.random.default_rng(17)
        a = rnd.integers(1, 2**63, BAND * BANDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        b = rnd.integers(1, 2**63, BAND * BANDS, dtype=np.uint64)
        for batch in batches:
            raw, off, valid = C.buffers(batch.column(2))
            ids = batch.column(0)
            for i, j in C.steps(off):
                w = C.Words(raw, off, valid & np.asarray(ids.is_valid()), i, j, C.SPACE)
                if not len(w.start):
                    continue
                # Lines.
                line = np.cumsum(w.data == 10)[w.start]
                new = np.concatenate([[True], (line[1:] != line[:-1]) | (w.row[1:] != w.row[:-1])])
                s = np.flatnonzero(new)
                e = np.append(s[1:], len(w.start))
                s, e = paragraphs(s, e, line, w.row)
                total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(w.hash * _pow(_P, len(w.hash)))])
                inv = _pow(_INV, len(w.hash) + 1)
                whole = lambda s, e: C.mix((total[e] - total[s]) * inv[s] + (e - s).astype(np.uint64) * C._C2)
                if len(s):
                    g = C.roll(w.hash, SHINGLE)
                    at = np.column_stack([s, e - SHINGLE + 1]).reshape(-1)
                    least = np.empty((len(s), BAND * BANDS), np.uint64)
                    for k in range(BAND * BANDS):
                        x = g * a[k] + b[k]
                        x ^= x >> np.uint64(29)
                        # One more, as paragraphs at the end stop behind the last shingle.
                        least[:, k] = np.minimum.reduceat(np.append(x, x[-1:]), at)[::2]
                    h = np.tile(np.arange(BANDS, dtype=np.uint64), (len(s), 1))
                    for k in range(BAND):
                        h = C.mix(h * np.uint64(31) + least[:, k::BAND])
                    distinct = np.array([len(np.unique(g[x : y - SHINGLE + 1])) for x, y in zip(s, e)])
                    bands = pa.ListArray.from_arrays(pa.array(np.arange(0, h.size + 1, BANDS, dtype=np.int32)), pa.array(h.reshape(-1).view(np.int64)))
                    at = pa.array(i + w.row[s])
                    yield pa.RecordBatch.from_arrays([ids.take(at), batch.column(1).take(at), pa.array(np.ones(len(s), bool)), pa.array(whole(s, e).view(np.int64)), pa.array(s - w.bounds[w.row[s]]), pa.array(e - w.bounds[w.row[s]]), pa.array(distinct), bands], PIECE)
                p = anchors(w)
                p = p[p + WINDOW <= len(w.row)]
                p = p[w.row[p] == w.row[p + WINDOW - 1]]
                if len(p):
                    at, none = pa.array(i + w.row[p]), pa.nulls(len(p), pa.int64())
                    yield pa.RecordBatch.from_arrays([ids.take(at), batch.column(1).take(at), pa.array(np.zeros(len(p), bool)), pa.array(whole(p, p + WINDOW).view(np.int64)), pa.array(p - w.bounds[w.row[p]]), none, none, pa.nulls(len(p), pa.list_(pa.int64()))], PIECE)

    return run


def setter():
    """mapInArrow function: id, w0, w1, text -> id, items: the shingle set of words w0 to w1 of text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, off, valid = C.buffers(batch.column(3))
            w0, w1 = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            for i, j in C.steps(off):
                w = C.Words(raw, off, valid, i, j, C.SPACE)
                items = [np.unique(C.roll(w.hash[w.bounds[r] + w0[i + r] : w.bounds[r] + w1[i + r]], SHINGLE)) for r in range(j - i)]
                yield C.set_batch(batch.column(0).slice(i, j - i), items)

    return run


def _passages(w0: np.ndarray, w1: np.ndarray, first_doc: np.ndarray, gone: np.ndarray) -> list[tuple]:
    """(first word, end word, first document, removed) of a text's passages: each word has the verdict of the last piece painted
    over it."""
    low = int(w0.min())
    over = np.full(int(w1.max()) - low, -1, np.int64)
    for k in np.lexsort((-first_doc, gone)).tolist():
        over[w0[k] - low : w1[k] - low] = k
    # Pieces of one verdict and first document are one kind.
    _, kind = np.unique(np.column_stack([first_doc, gone.astype(np.int64)]), axis=0, return_inverse=True)
    shown = np.where(over < 0, -1, kind.reshape(-1)[over])
    edge = np.flatnonzero(np.diff(shown)) + 1
    return [(a + low, b + low, int(first_doc[over[a]]), bool(gone[over[a]])) for a, b in zip([0, *edge.tolist()], [*edge.tolist(), len(over)]) if shown[a] >= 0]


def painter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow function: doc_id, text, pieces (w0, w1, first_doc, gone) -> passages, in code points of the text."""
    names = ["doc_id", "start", "end", "n_words", "first_doc", "removed"]
    types = [pa.int64()] * 5 + [pa.bool_()]
    for batch in batches:
        raw, off, valid = C.buffers(batch.column(1))
        ids, lists = batch.column(0).to_pylist(), batch.column(2)
        for i, j in C.steps(off):
            w = C.Words(raw, off, valid, i, j, C.SPACE, hashes=False)
            chars = np.concatenate([[0], np.cumsum((w.data & 0xC0) != 0x80)])
            rows = []
            for r in range(i, j):
                of = lists[r].values
                lo, base = int(w.bounds[r - i]), int(chars[off[r] - w.lo])
                for a, b, first, gone in _passages(*(of.field(c).to_numpy(zero_copy_only=False) for c in ("w0", "w1", "first_doc", "gone"))):
                    rows.append((ids[r], int(chars[w.start[lo + a]]) - base, int(chars[w.end[lo + b - 1]]) - base, b - a, first, gone))
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in rows], types[k]) for k in range(6)], names)


def looker(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow function: doc_id, key, text, spans (w0, w1) -> each span with the hashes of up to NEAR words before it (nearest
    first) and after it."""
    names, kinds = ["doc_id", "key", "w0", "w1", "lh", "rh"], [pa.int64()] * 4 + [pa.list_(pa.int64())] * 2
    for batch in batches:
        raw, off, valid = C.buffers(batch.column(2))
        ids, keys = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        for i, j in C.steps(off):
            w = C.Words(raw, off, valid, i, j, C.SPACE)
            rows = []
            for r in range(i, j):
                h = w.hash[int(w.bounds[r - i]) : int(w.bounds[r - i + 1])].view(np.int64)
                for span in batch.column(3)[r].as_py():
                    a, b = span["w0"], span["w1"]
                    rows.append((ids[r], keys[r], a, b, h[max(a - NEAR, 0) : a][::-1], h[b : b + NEAR]))
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in rows], kinds[k]) for k in range(6)], names)


def _extended(docs: DataFrame, hit: DataFrame) -> DataFrame:
    """hit(doc_id, key, w0, first, gone), windows that repeat -> the windows to remove as spans, each extended against its first
    occurrence, and those first occurrences as far; a first occurrence of whatever is removed stays."""
    first = [F.col(f"first.{c}").alias(f"f_{c}") for c in ("doc_id", "key")]
    gone = hit.filter("gone").select("key", "doc_id", "w0", (F.col("w0") + WINDOW).alias("w1"), *first, (F.col("w0") - F.col("first.w0")).alias("shift"))
    same = ["key", "doc_id", "f_key", "f_doc_id", "shift"]
    by = Window.partitionBy(*same).orderBy("w0")
    fresh = F.when(F.col("w0") <= F.max("w1").over(by.rowsBetween(Window.unboundedPreceding, -1)), 0).otherwise(1)
    spans = gone.withColumn("fresh", fresh).withColumn("span", F.sum("fresh").over(by)).groupBy(*same, "span").agg(F.min("w0").alias("w0"), F.max("w1").alias("w1"))
    spans = C.settle(spans.drop("span").withColumn("f_w0", F.col("w0") - F.col("shift")).withColumn("f_w1", F.col("w1") - F.col("shift")).drop("shift"), "passage-spans")
    at = ["doc_id", "key", "w0", "w1"]
    asked = spans.select(*at).union(spans.select(*(f"f_{c}" for c in at))).distinct().groupBy("doc_id", "key").agg(F.collect_list(F.struct("w0", "w1")).alias("spans"))
    schema = "doc_id long, key long, w0 long, w1 long, lh array<long>, rh array<long>"
    around = C.settle(docs.join(asked, ["doc_id", "key"]).select("doc_id", "key", "text", "spans").mapInArrow(looker, schema).dropDuplicates(at), "passage-around")
    both = spans.join(around, at).join(around.select(*(F.col(c).alias(f"f_{c}") for c in around.columns)), [f"f_{c}" for c in at])

    def equal(side: str):
        """How many words from the span outward are equal."""
        agree = F.zip_with(side, f"f_{side}", lambda x, y: F.coalesce(x == y, F.lit(False)))
        other = F.array_position(agree, False)
        return F.when(other > 0, other - 1).otherwise(F.size(side)).cast("int")

    both = C.settle(both.select(*at, *(f"f_{c}" for c in at), equal("lh").alias("x"), equal("rh").alias("y")), "passage-extended")
    own = both.select("doc_id", "key", (F.col("w0") - F.col("x")).alias("w0"), (F.col("w1") + F.col("y")).alias("w1"), F.col("f_doc_id").alias("first_doc"), F.lit(True).alias("gone"))
    kept = both.select(F.col("f_doc_id").alias("doc_id"), F.col("f_key").alias("key"), (F.col("f_w0") - F.col("x")).alias("w0"), (F.col("f_w1") + F.col("y")).alias("w1"), F.col("f_doc_id").alias("first_doc"), F.lit(False).alias("gone"))
    return own.union(kept)


def _repeats(rows: DataFrame, key: str, name: str) -> DataFrame:
    """rows(key column, doc_id, key, w0, ...) of what stands in two documents or more, with its first place, and whether it is another.

    Which keys repeat is found from ids alone; only rows of such keys are looked at again. The table of first places is written
    before it is joined, so that the adaptive planner may split a key that holds most rows."""
    often = rows.groupBy(key).agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")).filter("low < high").select(key)
    hit = C.settle(rows.join(C.settle(often, f"{name}-often"), key), f"{name}-repeats")
    first = C.settle(hit.groupBy(key).agg(F.min(F.struct("doc_id", "w0", "key")).alias("first")), f"{name}-first")
    return hit.join(first, key).withColumn("gone", (F.col("doc_id") != F.col("first.doc_id")) | (F.col("w0") != F.col("first.w0")))


def repeated_passages(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """docs(doc_id long, text) -> doc_id, start, end (code points), n_words, first_doc, removed: a row for each
    passage of a document that occurs in another document too, with one verdict and one first document."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("key", F.xxhash64("text"))
    schema = "doc_id long, key long, line boolean, print long, w0 long, w1 long, n long, bands array<long>"
    docs = docs.filter("doc_id is not null and text is not null")
    pieces = C.settle(docs.select("doc_id", "key", "text").mapInArrow(cutter(), schema), "passage-pieces")
    lines = pieces.filter("line")
    place = F.min(F.struct("doc_id", "w0", "w1", "key"))
    classes = C.settle(lines.groupBy(F.col("print").alias("id")).agg(place.alias("at"), F.first("n").alias("n"), F.first("bands").alias("bands")), "passage-classes")
    rows = classes.select("id", "n", F.explode("bands").alias("bucket"))
    busy = op3_minhash.shared_buckets(rows, "passage")
    wanted = classes.join(busy.select("id").distinct(), "id", "left_semi").select("id", F.col("at.doc_id").alias("doc_id"), F.col("at.key").alias("key"), F.col("at.w0").alias("w0"), F.col("at.w1").alias("w1"))
    sets = wanted.join(docs, ["doc_id", "key"]).select("id", "w0", "w1", "text").mapInArrow(setter(), C.SET_SCHEMA)
    sets = C.settle(sets, "passage-sets")
    comp = op3_minhash.linked(busy, sets.dropDuplicates(["id"]), percent, name="passage").select(F.col("id").alias("print"), "comp")
    C.drop(busy, sets, classes)
    clustered = lines.drop("bands", "n", "line").join(comp, "print", "left").withColumn("cluster", F.coalesce("comp", "print")).drop("comp", "print")
    hits = _repeats(C.settle(clustered, "passage-lines"), "cluster", "passage-lines")
    whole = hits.select("doc_id", "key", "w0", "w1", F.col("first.doc_id").alias("first_doc"), "gone")
    # Only windows that repeat meet their texts again.
    windows = _repeats(pieces.filter("not line").select("print", "doc_id", "key", "w0"), "print", "passage-windows")
    found = whole.union(_extended(docs, C.settle(windows.drop("print"), "passage-hits"))).distinct()
    found = found.groupBy("doc_id", "key").agg(F.collect_list(F.struct("w0", "w1", "first_doc", "gone")).alias("pieces"))  # of one text
    schema = "doc_id long, start long, end long, n_words long, first_doc long, removed boolean"
    return docs.join(found, ["doc_id", "key"]).select("doc_id", "text", "pieces").mapInArrow(painter, schema)

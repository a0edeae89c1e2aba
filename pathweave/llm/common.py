"""What the training-data operators share: shared-folder tables, word arrays over Arrow buffers, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one vectorised step looks at (a single longer text is one step).
STEP_BYTES = 1 << 19


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one where it is unset."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="pathweave-")
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df as a compressed table into the shared folder and read it again: later steps start from files
    that outlive any executor, and are computed once."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.settled_at = path
    return out


def drop(*tables: DataFrame) -> None:
    """Delete tables that settle() wrote, once all that was made from them has been written too."""
    for t in tables:
        path = t.sparkSession._jvm.org.apache.hadoop.fs.Path(t.settled_at)
        path.getFileSystem(t.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z only."""
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


# ------------------------------------------------------------------ byte classes
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: ASCII white space; every other byte belongs to a word.
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: All ASCII but digits and letters; bytes of other characters belong to words.
NOT_ALNUM = np.zeros(256, bool)
NOT_ALNUM[:128] = True
NOT_ALNUM[48:58] = NOT_ALNUM[65:91] = NOT_ALNUM[97:123] = False
_RND = np.random.default_rng(20240101)
_BYTE = _RND.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_C1, _C2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (shift-multiply)."""
    x = (x ^ (x >> np.uint64(30))) * _C1
    x = (x ^ (x >> np.uint64(27))) * _C2
    return x ^ (x >> np.uint64(31))


_POW = np.ones(64, np.uint64)
np.multiply.accumulate(np.full(63, _BASE), out=_POW[1:])


def _powers(n: int) -> np.ndarray:
    global _POW
    if n > len(_POW):
        grown = np.ones(max(n, 2 * len(_POW)), np.uint64)
        np.multiply.accumulate(np.full(len(grown) - 1, _BASE), out=grown[1:])
        _POW = grown
    return _POW


def buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, offsets (one more than rows) and validity of a string array, without a copy of the text."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    large = pa.types.is_large_string(col.type)
    if col.type not in (pa.string(), pa.large_string()):
        col = col.cast(pa.string())
    _, off, data = col.buffers()
    kind = np.int64 if large else np.int32
    offsets = np.frombuffer(off, kind, len(col) + 1 + col.offset)[col.offset :].astype(np.int64) if off is not None and len(col) else np.zeros(len(col) + 1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    valid = np.asarray(col.is_valid())
    return raw, offsets, valid


def steps(offsets: np.ndarray) -> Iterator[tuple[int, int]]:
    """Runs of rows of about STEP_BYTES of text."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + STEP_BYTES, "right")) - 1
        j = min(max(j, i + 1), n)
        yield i, j
        i = j


class Words:
    """Words of rows i..j: start and end byte (within raw), number of the row, 64-bit hash."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, valid: np.ndarray, i: int, j: int, sep: np.ndarray, lower: bool = True, hashes: bool = True):
        lo, hi = int(offsets[i]), int(offsets[j])
        data = raw[lo:hi]
        off = offsets[i : j + 1] - lo
        inside = ~sep[data]
        if not valid[i:j].all():
            for k in np.flatnonzero(~valid[i:j]):
                inside[off[k] : off[k + 1]] = False
        edge = np.zeros(len(data) + 1, bool)
        edge[off] = True
        first = inside.copy()
        if len(data):
            first[1:] &= ~inside[:-1] | edge[1 : len(data)]
        last = inside.copy()
        if len(data):
            last[:-1] &= ~inside[1:] | edge[1 : len(data)]
        self.start = np.flatnonzero(first)
        self.end = np.flatnonzero(last) + 1
        self.row = np.searchsorted(off, self.start, "right") - 1
        #: Words of row r: bounds[r] to bounds[r + 1].
        self.bounds = np.searchsorted(self.start, off)
        self.lo, self.data = lo, data
        if hashes:
            self.hash = np.zeros(0, np.uint64)
            if len(self.start):
                size = self.end - self.start
                at = np.repeat(self.start, size)
                pos = np.arange(len(at)) - np.repeat(np.cumsum(size) - size, size)
                v = _BYTE[(_LOWER[data] if lower else data)[at + pos]] * _powers(int(size.max()))[pos]
                self.hash = mix(np.add.reduceat(v, np.cumsum(size) - size) + size.astype(np.uint64) * _C1)


_STEP = np.uint64(0xD6E8FEB86659FD93)


def roll(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of k consecutive values; len(h) - k + 1 of them (none if fewer)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for i in range(k):
        out = out * _STEP + h[i : i + n]
    return mix(out)


def shingle_sets(w: Words, k: int) -> list[np.ndarray]:
    """The distinct k-word shingle hashes of each row, sorted; fewer words than k: the whole sequence as one."""
    all_ = roll(w.hash, k)
    out = []
    for a, b in zip(w.bounds[:-1], w.bounds[1:]):
        n = b - a
        if n == 0:
            out.append(np.zeros(0, np.uint64))
        elif n < k:
            out.append(roll(w.hash[a:b], int(n)) + np.uint64(n))
        else:
            s = np.sort(all_[a : b - k + 1])
            keep = np.empty(len(s), bool)
            keep[0] = True
            np.not_equal(s[1:], s[:-1], out=keep[1:])
            out.append(s[keep])
    return out


#: Words of a set's parity bitmap.
BITS = [f"bits_{i}" for i in range(8)]
SET_SCHEMA = "id long, items array<long>, " + ", ".join(f"{c} long" for c in BITS)


def parity_bits(items: np.ndarray) -> np.ndarray:
    """A bitmap in which each item flips one bit: two sets differ in at least as many items as their bitmaps in bits."""
    place = (mix(items) >> np.uint64(55)).astype(np.int64)
    return np.packbits((np.bincount(place, minlength=512) & 1).astype(np.uint8)).view(np.int64)


def set_batch(ids: pa.Array, sets: list[np.ndarray]) -> pa.RecordBatch:
    """Rows of SET_SCHEMA."""
    at = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
    items = np.concatenate([np.zeros(0, np.uint64), *sets]).view(np.int64)
    bits = np.array([parity_bits(s) for s in sets], np.int64).reshape(len(sets), len(BITS))
    return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(pa.array(at), pa.array(items)), *(pa.array(np.ascontiguousarray(bits[:, i])) for i in range(len(BITS)))], ["id", "items", *BITS])


# ------------------------------------------------------------------ components
def components(links: DataFrame, name: str) -> DataFrame:
    """(id, comp): for every id of links (a, b) the smallest id that can be reached.

    In each round an id takes the smallest label of its neighbours and its label's label (pointer jumping), and hands
    the former to the label it had too (hooking), so that whole trees meet at once and chains of any order shorten
    geometrically. Labels only fall, so rounds end by themselves, when none has changed. Labels are written to the
    shared folder each round, and the round before goes; the driver sees one count. Hot ids are pre-aggregated by min() or
    split by the adaptive join."""
    both = settle(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).filter("a <> b").distinct(), f"{name}-edges")
    written = label = settle(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("comp")), f"{name}-label")
    while True:
        near = both.join(label.select(F.col("id").alias("b"), "comp"), "b").groupBy(F.col("a").alias("id")).agg(F.min("comp").alias("near"))
        seen = settle(label.join(near, "id"), f"{name}-near")
        hook = seen.groupBy("comp").agg(F.min("near").alias("hook"))
        up = label.select(F.col("id").alias("comp"), F.col("comp").alias("up"))
        step = seen.join(up, "comp").join(hook.withColumnRenamed("comp", "id"), "id", "left")
        # least() skips nulls: ids that are nobody's label have no hook.
        step = settle(step.select("id", F.least("comp", "near", "up", "hook").alias("next"), F.col("comp").alias("was")), f"{name}-label")
        label = step.select("id", F.col("next").alias("comp"))
        drop(seen, written)
        written = step
        if step.filter("next <> was").limit(1).count() == 0:
            drop(both)
            return label


def joined(comp: DataFrame, links: DataFrame, name: str) -> DataFrame:
    """comp(id, comp), as components() gives it, after further links (a, b): rounds go over the components that these join, not
    over the links that are known already."""
    of = lambda c: comp.select(F.col("id").alias(c), F.col("comp").alias(f"{c}_comp"))
    ends = links.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("a_comp", "a").alias("a"), F.coalesce("b_comp", "b").alias("b"))
    top = components(ends, name)
    known = comp.join(top.select(F.col("id").alias("comp"), F.col("comp").alias("top")), "comp", "left").select("id", F.coalesce("top", "comp").alias("comp"))
    return settle(known.union(top.join(comp.select("id"), "id", "left_anti")), f"{name}-joined")

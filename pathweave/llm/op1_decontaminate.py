"""Benchmark decontamination: one Aho-Corasick automaton over the normalised benchmark windows.

Benchmark items and documents are lower-cased (A-Z) and reduced to words of digits, letters and non-ASCII characters.
The windows of an item (13 consecutive words, or the whole of a shorter item) are the automaton's patterns, each framed
by blanks; a document's words joined by blanks are scanned once. A hit's end gives the word it ends at, words give
offsets in the original text.

The windows go to the executors as a broadcast list of a checked size (BLOCK_BYTES); a larger benchmark is cut into
blocks of that size. A task takes some megabytes of texts at a time and scans them with one block's automaton after the other, so an
automaton is made at most once for so many texts; their hits meet in one row for each document.

Defined cases: a null text has no words; an item without words has no windows and can't occur; repeated items of equal
text all occur; null item_ids occur in no list; documents without a hit are returned with zeros and the digest of "".
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave.llm import common as C

WINDOW, BLOCK_BYTES, HELD = 13, 16 << 20, 4
_SEPARATE = bytes(32 if C.NOT_ALNUM[b] else b + 32 if 65 <= b <= 90 else b for b in range(256))
_AUTOMATA: dict = {}


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").translate(_SEPARATE).split()


def windows(items: Iterator[tuple], size: int) -> dict[bytes, set]:
    """Normalised window -> the items that have it."""
    out: dict[bytes, set] = {}
    for item, text in items:
        w = words(text)
        for i in range(max(1, len(w) - size + 1) if w else 0):
            out.setdefault(b" " + b" ".join(w[i : i + size]) + b" ", set()).add(item)
    return out


def _automaton(key: str, block):
    """The automaton of a block; a worker process holds those of the last few blocks."""
    if key not in _AUTOMATA:
        import ahocorasick

        a = ahocorasick.Automaton()
        for p, items in block.value.items():
            a.add_word(p.decode("latin-1"), (p.count(b" ") - 1, tuple(items)))
        a.make_automaton()
        while len(_AUTOMATA) >= HELD:
            _AUTOMATA.pop(next(iter(_AUTOMATA)))
        _AUTOMATA[key] = a
    return _AUTOMATA[key]


_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def scanner(parts: list):
    """mapInArrow function: doc_id, text -> doc_id, n_words, hit words as runs, their offsets, items."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text in held(batch.column(1)):
                yield scanned(batch.column(0).slice(text[0], len(text[1])), text[1])

    def held(col: pa.Array, most: int = 32 << 20) -> Iterator[tuple[int, list]]:
        """Runs of rows of about so many bytes of text: first row, texts."""
        start, texts, size = 0, [], 0
        for r, text in enumerate(col):
            texts.append(bytes(text.as_buffer()) if text.is_valid else None)
            size += len(texts[-1] or b"")
            if size >= most:
                yield start, texts
                start, texts, size = r + 1, [], 0
        if texts:
            yield start, texts

    def scanned(ids: pa.Array, texts: list) -> pa.RecordBatch:
        n_words, lines = [], []
        for text in texts:
            w = text.translate(_SEPARATE).split() if text is not None else []
            n_words.append(len(w))
            lines.append(" " + b" ".join(w).decode("latin-1") + " " if w else "")
        found, at = [set() for _ in texts], [[] for _ in texts]
        # Every block's automaton meets all of these texts before the next one does.
        for part in parts:
            auto = _automaton(*part)
            if not len(auto):
                continue
            for r, line in enumerate(lines):
                for end, (size, who) in auto.iter(line) if line else ():
                    at[r].append((end, size))
                    found[r].update(who)
        runs, spans, items = [], [], []
        for text, line, hits, who, n in zip(texts, lines, at, found, n_words):
            if not hits:
                runs.append([]), spans.append([]), items.append([])
                continue
            blanks = np.flatnonzero(np.frombuffer(line.encode("latin-1"), np.uint8) == 32)
            hit = np.zeros(n + 1, np.int64)
            for end, size in hits:
                last = int(np.searchsorted(blanks, end))  # words before this blank
                hit[last - size] += 1
                hit[last] -= 1
            mask = np.cumsum(hit[:-1]) > 0
            edge = np.flatnonzero(np.diff(np.concatenate([[0], mask.astype(np.int8), [0]])))
            pairs = [(int(a), int(b)) for a, b in zip(edge[::2], edge[1::2])]
            places = [m.span() for m in _WORD.finditer(text.decode("utf-8", "replace").translate(_FOLD))]
            runs.append([x for p in pairs for x in p])
            spans.append([x for a, b in pairs for x in (places[a][0], places[b - 1][1])])
            items.append(sorted(x for x in who if x is not None))
        return pa.RecordBatch.from_arrays(
            [ids, pa.array(n_words, pa.int64()), pa.array(runs, pa.list_(pa.int64())), pa.array(spans, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))],
            ["doc_id", "n_words", "runs", "spans", "items"],
        )

    return run


def blocks(bench: DataFrame, size: int, block_bytes: int) -> Iterator[dict[bytes, set]]:
    """The benchmark's windows in blocks of a checked size; items come to the driver one partition at a time."""
    held, total = {}, 0
    for row in bench.select(F.col("item_id").cast("string"), F.col("text").cast("string")).toLocalIterator():
        for p, who in windows([(row[0], row[1])], size).items():
            if p not in held:
                held[p] = set()
                total += len(p)
            held[p] |= who
        if total >= block_bytes:
            yield held
            held, total = {}, 0
    yield held


def sent(spark: SparkSession, bench: DataFrame, size: int, block_bytes: int) -> list:
    """(key, broadcast) of each block; a key names the block's content."""
    parts = []
    for held in blocks(bench, size, block_bytes):
        content = b"".join(sorted(held)) + repr([sorted(str(i) for i in held[p]) for p in sorted(held)]).encode()
        parts.append((hashlib.sha256(content).hexdigest(), spark.sparkContext.broadcast(held)))
    return parts


def scan(docs: DataFrame, bench: DataFrame, size: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs(doc_id, text), bench(item_id, text) -> doc_id, n_words, runs (start and end word of each hit run), spans
    (their offsets in the original, in code points), items; one row for each row of docs."""
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    parts = sent(docs.sparkSession, bench, size, block_bytes)
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words long, runs array<long>, spans array<long>, items array<string>"
    return docs.mapInArrow(scanner(parts), schema)


def clean(docs: DataFrame, bench: DataFrame, size: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of docs, whole, that are not contaminated."""
    parts = sent(docs.sparkSession, bench, size, block_bytes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanned = scanner(parts)
        for batch in batches:
            at = [batch.schema.get_field_index(c) for c in ("doc_id", "text")]
            keep: list[bool] = []
            for found in scanned(iter([pa.RecordBatch.from_arrays([batch.column(i) for i in at], ["doc_id", "text"])])):
                hit = [sum(r[1::2]) - sum(r[::2]) for r in found.column(2).to_pylist()]
                keep += [not (h > 0 and 20 * h >= n) for h, n in zip(hit, found.column(1).to_pylist())]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def report(scanned: DataFrame) -> DataFrame:
    """Counts, digest and the verdict: hit words are a twentieth of all words at least."""
    hit = F.aggregate(F.sequence(F.lit(0), F.greatest(F.size("runs") - 1, F.lit(0))), F.lit(0).cast("long"), lambda s, i: s + F.coalesce(F.get("runs", i), F.lit(0)) * (2 * (i % 2) - 1))
    out = scanned.withColumn("n_hit", hit)
    return out.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (F.col("n_hit") * 20 >= F.col("n_words"))).alias("contaminated"), "spans",
    )

"""Best-fit packing with exact-complement hashing.

Documents become token ids (ended by id 0); those longer than a sequence are cut into full pieces and a rest. What
is packed are lengths, not documents: the plan is made on the histogram of lengths (as many numbers as a sequence
has tokens, whatever the corpus), on the driver. Planning goes from the longest length down: the gap that a piece
leaves is looked up among single lengths, then among pair sums, then triple sums of what is still available; a
combination that fills the gap exactly is used as often as its counts allow. What has no exact complement is packed by
best fit decreasing, in runs of equal lengths.

Every step of the plan holds for a whole run of equal sequences, so plan rows grow with the number of lengths and
not with the corpus. Pieces then find their places by their rank among pieces of their length: ranks come from counts
by (partition, length), so no length is gathered in one task, however common it is.

Defined cases: null text counts as empty and yields one piece of id 0; repeated rows are packed as often as they occur;
an empty table yields no rows.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathweave.llm import common as C

CAPACITY, VOCABULARY = 2048, "word_bpe_49k.json"

# ------------------------------------------------------------------ tokens
# A text is plain if its bytes are printable ASCII without "<" (which could begin a special token), tab or line ends, and
# Latin-1 letters and signs whose word class and lower case are the same for every Unicode version. Plain texts are split
# with array operations into the words of the tokenizer's own pattern, and each distinct word is encoded once; all other
# texts go through the tokenizer as they are.
_SPACE, _LETTER, _DIGIT, _SIGN = 0, 1, 2, 3
_CLASS = np.full(256, _SIGN, np.uint8)
_CLASS[[9, 10, 13, 32]] = _SPACE
_CLASS[48:58] = _DIGIT
_CLASS[65:91] = _CLASS[97:123] = _CLASS[0xC3] = _LETTER
_OTHER = np.ones(256, bool)  # bytes that no plain text has
_OTHER[[9, 10, 13, 0xC2, 0xC3]] = _OTHER[32:127] = _OTHER[128:192] = False
_OTHER[ord("<")] = True
_SIGNS = np.zeros(256, bool)  # what may follow 0xC2
_SIGNS[[*range(0xA1, 0xA8), 0xA9, 0xAB, 0xAC, 0xAE, 0xB0, 0xB1, 0xB6, 0xB7, 0xBB, 0xBF]] = True
CACHED_WORDS = 300_000


def _byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: printable ones for themselves, others from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class Tokens:
    """Token ids of texts; words are remembered, as most text consists of words that were seen before."""

    def __init__(self, vocabulary: str = VOCABULARY):
        import public_tokenizers
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(public_tokenizers.path(vocabulary))
        self.split = vocabulary == VOCABULARY
        self.letters = _byte_letters()
        self.forget()

    def forget(self) -> None:
        self.slot: dict[int, int] = {}
        self.at, self.size, self.flat = np.zeros(1 << 12, np.int64), np.zeros(1 << 12, np.int64), np.zeros(1 << 14, np.uint32)
        self.used = 0

    def direct(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32)

    def learn(self, keys: list[int], words: list[bytes]) -> None:
        tokenize, letters = self.tokenizer.model.tokenize, self.letters
        flat, size, k = [], [], len(self.slot)
        for word in words:
            ids = [t.id for t in tokenize(word.decode() if word.isascii() else "".join([letters[b] for b in word]))]
            flat += ids
            size.append(len(ids))
        while k + len(size) > len(self.at):
            self.at, self.size = np.resize(self.at, 2 * len(self.at)), np.resize(self.size, 2 * len(self.size))
        while self.used + len(flat) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        ends = np.cumsum(size)
        self.at[k : k + len(size)], self.size[k : k + len(size)] = self.used + ends - size, size
        self.flat[self.used : self.used + len(flat)] = flat
        self.used += len(flat)
        self.slot.update(zip(keys, range(k, k + len(size))))

    def plain(self, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Which of the texts data[off[r]:off[r + 1]] are plain."""
        odd = _OTHER[data]
        if len(data):
            lead = np.flatnonzero((data[:-1] == 0xC2) | (data[:-1] == 0xC3))
            after = data[lead + 1]
            two = data[lead] == 0xC2
            odd[lead[two & ~_SIGNS[after] | ~two & ((after == 0x97) | (after == 0xB7))]] = True
        bad = np.concatenate([[0], np.cumsum(odd)])
        return bad[off[1:]] == bad[off[:-1]]

    def split_words(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and sizes of words, and the bytes in lower case."""
        data = C._LOWER[data]
        after_c3 = np.flatnonzero(data[:-1] == 0xC3) + 1
        low = data[after_c3]
        data[after_c3] = np.where((low >= 0x80) & (low <= 0x9E), low + 0x20, low)
        kind = _CLASS[data]
        kind[after_c3] = _LETTER
        edge = np.zeros(len(data) + 1, bool)
        edge[off] = True
        inside = kind != _SPACE
        start = inside.copy()
        start[1:] &= (kind[1:] != kind[:-1]) | edge[1:-1] | (kind[1:] == _DIGIT)
        # An apostrophe that begins a word takes s, t, m, d, re, ve or ll with it.
        for p in np.flatnonzero((data == 39) & start):
            stop = p + 1
            while stop < min(p + 3, len(data)) and not edge[stop]:
                stop += 1
            tail = data[p + 1 : stop].tobytes()
            n = 1 if tail[:1] in (b"s", b"t", b"m", b"d") else 2 if tail in (b"re", b"ve", b"ll") else 0
            if n:
                start[p + 1 : p + 1 + n] = False
                if p + 1 + n < len(data) and inside[p + 1 + n]:
                    start[p + 1 + n] = True
        at = np.flatnonzero(start)
        size = np.add.reduceat(inside, at, dtype=np.int64) if len(at) else at
        return at, size, data

    def many(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of plain texts, one after the other, and where each text's ids begin (one more than texts)."""
        at, size, data = self.split_words(data, off)
        if not len(at):
            return np.zeros(0, np.uint32), np.zeros(len(off), np.int64)
        total = np.cumsum(size) - size
        pos = np.arange(int(size.sum())) - np.repeat(total, size)
        value = C._BYTE[data[np.repeat(at, size) + pos]] * C._powers(int(size.max()))[pos]
        key = C.mix(np.add.reduceat(value, total) + size.astype(np.uint64) * C._C1)
        keys, first, back = np.unique(key, return_index=True, return_inverse=True)
        if len(self.slot) > CACHED_WORDS:
            self.forget()
        wanted = keys.tolist()
        known = self.slot.get
        slots = np.array([known(k, -1) for k in wanted], np.int64)
        new = np.flatnonzero(slots < 0)
        if len(new):
            raw, one = data.tobytes(), first[new]
            begin, stop = at[one].tolist(), (at[one] + size[one]).tolist()
            slots[new] = np.arange(len(new)) + len(self.slot)
            self.learn(keys[new].tolist(), [raw[a:b] for a, b in zip(begin, stop)])
        slot = slots[back]
        count = self.size[slot]
        ends = np.cumsum(count)
        ids = self.flat[np.arange(int(ends[-1])) + np.repeat(self.at[slot] - (ends - count), count)]
        words_before = np.searchsorted(at, off)
        return ids, np.concatenate([[0], ends])[words_before]


_TOKENS: dict[str, Tokens] = {}


def pieces_of(capacity: int, vocabulary: str, with_ids: bool):
    """mapInArrow function: doc_id, text -> a row for each piece."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        if vocabulary not in _TOKENS:
            _TOKENS[vocabulary] = Tokens(vocabulary)
        tokens = _TOKENS[vocabulary]
        for batch in batches:
            row, piece, start, length, crc, ids = [], [], [], [], [], []
            raw, off, valid = C.buffers(batch.column(1))

            def cut(r: int, own: np.ndarray) -> None:
                data = np.append(own, np.uint32(0)).astype("<u4").tobytes()
                for p, at in enumerate(range(0, len(data), 4 * capacity)):
                    part = data[at : at + 4 * capacity]
                    row.append(r), piece.append(p), start.append(at // 4), length.append(len(part) // 4), crc.append(zlib.crc32(part))
                    if with_ids:
                        ids.append(np.frombuffer(part, "<u4").astype(np.int32))

            for i, j in C.steps(off):
                data, own = raw[off[i] : off[j]], off[i : j + 1] - off[i]
                plain = tokens.plain(data, own) & valid[i:j] & tokens.split
                many, begin = np.zeros(0, np.uint32), None
                if plain.any():
                    # Texts that aren't plain count as blank here.
                    if not plain.all():
                        data = data.copy()
                        for r in np.flatnonzero(~plain):
                            data[own[r] : own[r + 1]] = 32
                    many, begin = tokens.many(data, own)
                for r in range(j - i):
                    if not valid[i + r]:
                        cut(i + r, np.zeros(0, np.uint32))
                    elif plain[r]:
                        cut(i + r, many[begin[r] : begin[r + 1]])
                    else:
                        cut(i + r, tokens.direct(batch.column(1)[i + r].as_py()))
            cols = [batch.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if with_ids:
                cols, names = [*cols, pa.array(ids, pa.list_(pa.int32()))], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(cols, names)

    return run


# ------------------------------------------------------------------ the plan
def plan(histogram: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """(lengths of a sequence, how many such sequences) over all pieces of the histogram."""
    left = np.zeros(capacity + 1, np.int64)
    for n, c in histogram.items():
        left[n] = c
    out: list[tuple[tuple[int, ...], int]] = []

    def use(combination: tuple[int, ...]) -> bool:
        need: dict[int, int] = {}
        for n in combination:
            need[n] = need.get(n, 0) + 1
        times = min(int(left[n]) // k for n, k in need.items())
        if times:
            for n, k in need.items():
                left[n] -= times * k
            out.append((combination, times))
        return times > 0

    if left[capacity]:
        use((capacity,))
    # Pair sums: for a gap g, the pairs (a, g - a) with both lengths available. Lengths are integers up to the capacity, so
    # the index of pair sums is the array of available lengths seen from both ends; triples put one length in front of it.
    for n in range(capacity - 1, 0, -1):
        while left[n]:
            gap = capacity - n
            if left[gap] and use((n, gap)):
                continue
            a = np.flatnonzero(left[1 : gap // 2 + 1]) + 1
            a = a[left[gap - a] > 0]
            if any(use((n, int(gap - x), int(x))) for x in a[::-1]):
                continue
            done = False
            for big in (np.flatnonzero(left[1:gap]) + 1)[::-1]:
                rest = int(gap - big)
                b = np.flatnonzero(left[1 : rest // 2 + 1]) + 1
                b = b[left[rest - b] > 0]
                if any(use((n, int(big), int(rest - x), int(x))) for x in b[::-1]):
                    done = True
                    break
            if not done:
                break
    # Residuals: best fit decreasing over runs of equal sequences; open[g] holds the runs whose gap is g.
    runs: list[list] = []
    open_: dict[int, list[int]] = {}
    for n in range(capacity, 0, -1):
        while left[n]:
            gap = min((g for g in open_ if g >= n and open_[g]), default=None)
            if gap is None:
                per = capacity // n
                if left[n] >= per:
                    runs.append([(n,) * per, int(left[n]) // per])
                else:
                    runs.append([(n,) * int(left[n]), 1])
                lengths, times = runs[-1]
                left[n] -= len(lengths) * times
                r = len(runs) - 1
            else:
                r = open_[gap].pop()
                lengths, times = runs[r]
                fit = min(gap // n, max(1, int(left[n]) // times))
                took = min(times, int(left[n]) // fit)
                if took < times:
                    runs.append([lengths, times - took])
                    open_.setdefault(gap, []).append(len(runs) - 1)
                runs[r] = [lengths + (n,) * fit, took]
                left[n] -= fit * took
            rest = capacity - sum(runs[r][0])
            if rest:
                open_.setdefault(rest, []).append(r)
    return out + [(tuple(x), t) for x, t in runs]


def slots(planned: list[tuple[tuple[int, ...], int]], capacity: int) -> dict[int, np.ndarray]:
    """For each length: rows (first rank, first sequence, place); ranks from there on go to consecutive sequences."""
    out: dict[int, list] = {}
    rank = [0] * (capacity + 1)
    sequence = 0
    for lengths, times in planned:
        at = 0
        for n in lengths:
            out.setdefault(n, []).append((rank[n], sequence, at))
            rank[n] += times
            at += n
        sequence += times
    return {n: np.array(v, np.int64).reshape(-1, 3) for n, v in out.items()}


def placer(places):
    """mapInArrow function over one partition: gives pieces their sequence and place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.column(batch.schema.get_field_index("length")).to_numpy()
            rank = batch.column(batch.schema.get_field_index("rank")).to_numpy()
            sequence, place = np.zeros(len(n), np.int64), np.zeros(len(n), np.int64)
            for length in np.unique(n):
                at = np.flatnonzero(n == length)
                table = places.value[int(length)]
                k = np.searchsorted(table[:, 0], rank[at], "right") - 1
                sequence[at] = table[k, 1] + rank[at] - table[k, 0]
                place[at] = table[k, 2]
            keep = [i for i, f in enumerate(batch.schema.names) if f != "rank"]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(sequence), pa.array(place)], [*(batch.schema.names[i] for i in keep), "sequence_id", "offset"])

    return run


def ranker():
    """mapInArrow function over one partition: numbers the pieces of each length from 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seen = TaskContext.get().partitionId(), {}
        for batch in batches:
            n = batch.column(batch.schema.get_field_index("length")).to_numpy()
            local = np.zeros(len(n), np.int64)
            for length in np.unique(n):
                at = np.flatnonzero(n == length)
                local[at] = np.arange(len(at)) + seen.get(int(length), 0)
                seen[int(length)] = seen.get(int(length), 0) + len(at)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(n), part, np.int64)), pa.array(local)], [*batch.schema.names, "part", "local"])

    return run


def pack(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str = VOCABULARY, with_ids: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32, (ids,) sequence_id, offset."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    made = docs.mapInArrow(pieces_of(capacity, vocabulary, with_ids), schema).mapInArrow(ranker(), schema + ", part long, local long")
    made = C.settle(made, "packing-pieces")
    # At most as many rows as the sequence has tokens reach the driver, however large the corpus.
    histogram = {r["length"]: r["n"] for r in made.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    places = spark.sparkContext.broadcast(slots(plan(histogram, capacity), capacity))
    # Ranks: the count of a length in earlier partitions; the running sum goes over the (part, length) counts only.
    per = made.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    before = per.withColumn("before", F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    ranked = made.join(before.select("length", "part", "before"), ["length", "part"]).withColumn("rank", F.col("before") + F.col("local"))
    ranked = ranked.select(*[f.split()[0] for f in schema.split(", ")], "rank")
    return ranked.mapInArrow(placer(places), schema + ", sequence_id long, offset long")

"""MinHash near-duplicates by tensored banding.

A plain banding scheme with T tables of keys of 2t minhashes computes 2tT of them. Here two families of m
collisions (each of t minhashes) are computed, 2tm minhashes in all, and the key of table (i, j) combines
collision i of the first with collision j of the second: m * m tables. With t = 2 and m = 8, 32 minhashes make 64
tables, and a pair of similarity 0.85 is missed with probability 7e-5, at 0.9 with 5e-6.

Texts with equal shingle sets form one class first; only a class goes on. Table keys are combined only from collisions
that another class has too. Candidates are confirmed on full sets. Each set is
paired with the smallest and the most frequent of the pivots (smallest members) of its buckets. What is then still in different components is paired across components: in full in buckets of
a few members; the sets of larger mixed buckets go through a prefix filter, which is exact: two sets as similar as asked
share one of the rarest items of each. Rows that no other row of their item can match go before they are paired, and pairs are made
only where sizes, positions and the differing bits of two parity bitmaps allow the similarity, all of them
bounds. So a bucket emits about its links, not the square of its members, and no colliding pair between components stays
unchecked.

Defined cases: null or empty text has the empty set, is linked with nothing and is its own component; repeated rows
stay rows; an id that comes with several texts is one document with the links of all of them; a null doc_id is treated as
an id that is linked with nothing; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathweave.llm import common as C

K_WORDS, GROUP, FAMILY, SMALL_BUCKET, PIVOT_ROUNDS, PIVOTS = 5, 2, 8, 12, 2, 6


def signer(k_words: int, group: int, family: int, seed: int = 7):
    """mapInArrow function: doc_id, text -> doc_id, n_shingles, set_id (two words), parts (2 * family collisions)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rnd = np.random.default_rng(seed)
        n_hash = 2 * family * group
        a = rnd.integers(1, 2**63, n_hash, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        b = rnd.integers(1, 2**63, n_hash, dtype=np.uint64)
        place = np.arange(2 * family, dtype=np.uint64)
        for batch in batches:
            raw, off, valid = C.buffers(batch.column(1))
            ids = batch.column(0)
            for i, j in C.steps(off):
                sets = C.shingle_sets(C.Words(raw, off, valid, i, j, C.SPACE), k_words)
                n = np.array([len(s) for s in sets], np.int64)
                sig = np.zeros((len(sets), 2 * family), np.uint64)
                one, two = np.zeros(len(sets), np.uint64), np.zeros(len(sets), np.uint64)
                for r, s in enumerate(sets):
                    if len(s):
                        one[r], two[r] = set_hash(s)
                        least = np.full(n_hash, np.uint64(2**64 - 1))
                        for c in range(0, len(s), 8192):
                            x = s[c : c + 8192] * a[:, None]
                            x += b[:, None]
                            x ^= x >> np.uint64(29)
                            np.minimum(least, x.min(axis=1), out=least)
                        g = least.reshape(2 * family, group)
                        h = place
                        for c in range(group):
                            h = C.mix(h * np.uint64(31) + g[:, c])
                        sig[r] = h
                parts = pa.ListArray.from_arrays(pa.array(np.arange(0, sig.size + 1, 2 * family, dtype=np.int32)), pa.array(sig.reshape(-1).view(np.int64)))
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array(n), pa.array(one.view(np.int64)), pa.array(two.view(np.int64)), parts], ["doc_id", "n_shingles", "set_1", "set_2", "parts"])

    return run


def setter(k_words: int):
    """mapInArrow function: id, n, set_1, set_2, text -> id, items (the full set), bits; texts of another set than the named
    one are left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, off, valid = C.buffers(batch.column(4))
            named = [batch.column(c).to_numpy() for c in (1, 2, 3)]
            for i, j in C.steps(off):
                sets = C.shingle_sets(C.Words(raw, off, valid, i, j, C.SPACE), k_words)
                own = [r for r, s in enumerate(sets) if (len(s), *(int(x.view(np.int64)) for x in set_hash(s))) == tuple(int(x[i + r]) for x in named)]
                yield C.set_batch(batch.column(0).take(pa.array([i + r for r in own], pa.int64())), [sets[r] for r in own])

    return run


def set_hash(s: np.ndarray) -> tuple[np.uint64, np.uint64]:
    """Two words that name a set of items."""
    return (np.add.reduce(C.mix(s)), np.bitwise_xor.reduce(C.mix(s + np.uint64(1)))) if len(s) else (np.uint64(0), np.uint64(0))


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those of pairs (a, b) whose full sets are similar enough."""
    left = sets.select(F.col("id").alias("a"), F.col("items").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("items").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", both.alias("both"), (F.size("x") + F.size("y") - both).alias("either")).filter(F.col("both") * 100 >= F.col("either") * percent).select("a", "b")


def _mixed(placed: DataFrame, key: str) -> DataFrame:
    """Keys whose members are in more than one component: members in all, and the component with most of them."""
    parts = placed.groupBy(key, "comp").agg(F.count(F.lit(1)).alias("size"))
    return parts.groupBy(key).agg(F.count(F.lit(1)).alias("parts"), F.sum("size").alias("members"), F.max(F.struct("size", "comp")).alias("top")).filter("parts > 1").select(key, "members", F.col("top.comp").alias("top"))


def _alike(percent: int) -> Column:
    """Whether the sizes of two sets, what is left of them from a shared item on, and the bits in which they differ allow the
    similarity. Each is a bound, so no pair that is similar enough goes."""
    total = F.col("un") + F.col("n")
    differ = sum((F.bit_count(F.col(c).bitwiseXOR(F.col(f"u{c}"))) for c in C.BITS), F.lit(0))
    return (
        (F.least("un", "n") * 100 >= F.greatest("un", "n") * percent)
        & (F.least("ua", "after") * (100 + percent) >= total * percent)
        # Sets of similarity s differ in (1 - s) / (1 + s) of both sizes together.
        & (differ * (100 + percent) <= total * (100 - percent))
    )


def _met(few: DataFrame, rest: DataFrame, key: str, percent: int) -> DataFrame:
    """Pairs (a, b) of few and rest that share a key, are in different components and may be similar enough.
    after: how many items of a set come at the key or after it; their lesser number bounds what is shared."""
    few = few.select(key, F.col("id").alias("u"), F.col("n").alias("un"), F.col("comp").alias("uc"), F.col("after").alias("ua"), *[F.col(c).alias(f"u{c}") for c in C.BITS])
    return few.join(rest, key).filter((F.col("comp") != F.col("uc")) & _alike(percent)).select(F.least("u", "id").alias("a"), F.greatest("u", "id").alias("b")).distinct()


def _across(rest: DataFrame, key: str, percent: int) -> DataFrame:
    """Pairs of one key in different components: members outside the key's largest component, with all."""
    return _met(rest.filter("comp <> top"), rest, key, percent)


def _pivots(rare: DataFrame, turn: int, percent: int) -> DataFrame:
    """Pairs of a few members of each item, drawn by hash, with those of other components."""
    drawn = [F.min_by(F.struct("id", "n", "comp", "after", *C.BITS), F.struct(F.xxhash64("id", "item", F.lit(turn * PIVOTS + i)), "id")) for i in range(PIVOTS)]
    few = rare.groupBy("item").agg(F.array_distinct(F.array(*drawn)).alias("p")).select("item", F.explode("p").alias("p")).select("item", "p.*")
    return _met(few, rare, "item", percent)


def _rare_items(many: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The rarest items of each set, so many that two similar sets must share one of them."""
    items = many.join(sets.select("id", "items"), "id").select("id", "n", "comp", F.explode("items").alias("item"))
    count = items.groupBy("item").agg(F.count(F.lit(1)).alias("df"))
    order = Window.partitionBy("id").orderBy("df", "item")
    ranked = items.join(count, "item").withColumn("at", F.row_number().over(order))
    # n - ceil(n * percent / 100) + 1 items.
    return ranked.filter("df > 1").filter(F.col("at") <= F.col("n") - F.ceil(F.col("n") * percent / F.lit(100)) + 1).select("item", "id", "n", "comp", (F.col("n") - F.col("at") + 1).alias("after"))


def _pruned(rare: DataFrame, percent: int) -> DataFrame:
    """Without the rows that no other row of their item can be similar enough to, as far as the item's sizes and what is left
    from it on tell, and without items whose rows are all of one component. A set with many items of its own is left
    with no row here, before it is paired with anything."""
    of = rare.groupBy("item").agg(F.min("n").alias("least_n"), F.max("after").alias("most_after"), F.min("comp").alias("low"), F.max("comp").alias("high")).filter("low <> high")
    other = F.greatest("least_n", F.ceil(F.col("n") * percent / F.lit(100)))
    return rare.join(of, "item").filter(F.least("after", "most_after") * (100 + percent) >= (F.col("n") + other) * percent).select(*rare.columns)


def linked(busy: DataFrame, sets: DataFrame, percent: int, small_bucket: int = SMALL_BUCKET, name: str = "near") -> DataFrame:
    """busy(bucket, id, n, pivot), sets(id, items, bits) -> (id, comp) of all ids that have a link."""
    bits = sets.select("id", *C.BITS)
    # Two pairs for each set, whatever the number of its buckets: the smallest of their pivots, and the most frequent one.
    centres = busy.groupBy("id").agg(F.min("pivot").alias("least"), F.mode("pivot", True).alias("most"))
    stars = centres.select("id", F.explode(F.array_distinct(F.array("least.id", "most.id"))).alias("pivot")).filter("id <> pivot")
    stars = C.settle(stars.select(F.least("pivot", "id").alias("a"), F.greatest("pivot", "id").alias("b")).distinct(), f"{name}-stars")
    links = C.settle(_confirmed(stars, sets, percent), f"{name}-links")
    comp = C.components(links, f"{name}-one")
    placed = busy.join(comp, "id", "left").select("bucket", "id", "n", F.coalesce("comp", "id").alias("comp"), F.col("n").alias("after"))
    mixed = _mixed(placed, "bucket")
    rest = C.settle(placed.join(mixed, "bucket"), f"{name}-rest")
    few = _across(rest.filter(F.col("members") <= small_bucket).join(bits, "id"), "bucket", percent)
    many = rest.filter(F.col("members") > small_bucket).select("id", "n", "comp").distinct()
    once = C.settle(_pruned(_rare_items(many, sets, percent), percent), f"{name}-rare")
    rare = C.settle(_pruned(once, percent).join(bits, "id"), f"{name}-rare")
    C.drop(once)
    # Before rare items are paired in full, a few members of each, drawn anew each turn, are paired with the others: components
    # meet here with pairs in the number of members. Turns end when they find little more; what is left is paired in full.
    ids = rare.select("id").distinct().count()
    for turn in range(PIVOT_ROUNDS if ids else 0):
        met = C.settle(_confirmed(_pivots(rare, turn, percent), sets, percent), f"{name}-met")
        comp = C.joined(comp, met, f"{name}-met")
        if met.count() * 50 < ids:
            break
        was = rare
        rare = rare.drop("comp").join(comp, "id", "left").select("item", "id", "n", F.coalesce("comp", "id").alias("comp"), "after", *C.BITS)
        rare = C.settle(_pruned(rare, percent), f"{name}-rare")
        C.drop(was)
    cross = few.union(_across(rare.join(_mixed(rare, "item"), "item"), "item", percent)).distinct().join(stars, ["a", "b"], "left_anti")
    more = C.settle(_confirmed(cross, sets, percent), f"{name}-more")
    C.drop(rest, rare, stars, links)
    return C.joined(comp, more, f"{name}-two")


def shared_buckets(rows: DataFrame, name: str) -> DataFrame:
    """rows(bucket, id, n) -> (bucket, id, n, pivot) of buckets with two members or more; pivot: n and id of the smallest."""
    busy = rows.groupBy("bucket").agg(F.count(F.lit(1)).alias("members"), F.min(F.struct("n", "id")).alias("pivot")).filter("members > 1")
    return C.settle(rows.join(busy, "bucket").select("bucket", "id", "n", "pivot"), f"{name}-buckets")


def tables(classes: DataFrame, family: int, name: str = "near") -> DataFrame:
    """classes(id, n, parts) -> busy buckets.

    A bucket of table (i, j) can only be shared by sets that share collision i and collision j, so keys are combined from
    collisions that more than one set has: 2 * family rows for each set are shuffled, not family * family."""
    parts = classes.select("id", F.explode("parts").alias("part"))
    shared = parts.groupBy("part").agg(F.count(F.lit(1)).alias("members")).filter("members > 1")
    live = parts.join(shared, "part").groupBy("id").agg(F.collect_set("part").alias("live"))  # 2 * family at most
    own = lambda start: F.filter(F.slice("parts", start, family), lambda x: F.array_contains("live", x))
    keys = F.flatten(F.transform(own(1), lambda x: F.transform(own(family + 1), lambda y: F.xxhash64(x, y))))
    rows = C.settle(classes.join(live, "id").select("id", "n", F.explode(keys).alias("bucket")), f"{name}-keys")
    busy = shared_buckets(rows, name)
    C.drop(rows)
    return busy


def near_duplicates(docs: DataFrame, percent: int = 85, k_words: int = K_WORDS, group: int = GROUP, family: int = FAMILY, small_bucket: int = SMALL_BUCKET) -> DataFrame:
    """docs(doc_id long, text) -> doc_id, n_shingles, component_id, kept; one row for each row of docs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, n_shingles long, set_1 long, set_2 long, parts array<long>"
    signed = C.settle(docs.mapInArrow(signer(k_words, group, family), schema), "near-signed")
    key = ["n_shingles", "set_1", "set_2"]
    # A class is a set of shingles; its number is its own, as an id may come with several texts.
    classes = signed.filter("n_shingles > 0 and doc_id is not null").groupBy(*key).agg(F.min("doc_id").alias("first_doc"), F.first("parts").alias("parts"))
    classes = C.settle(classes.withColumn("id", F.monotonically_increasing_id()), "near-classes")
    busy = tables(classes.select("id", F.col("n_shingles").alias("n"), "parts"), family)

    wanted = classes.select("id", *key, F.col("first_doc").alias("doc_id")).join(busy.select("id").distinct(), "id", "left_semi")
    texts = docs.join(wanted, "doc_id").select("id", *key, "text")
    sets = texts.mapInArrow(setter(k_words), C.SET_SCHEMA)
    sets = C.settle(sets.dropDuplicates(["id"]), "near-sets")

    comp = linked(busy, sets, percent, small_bucket)
    C.drop(busy, sets)
    # Ids with several texts: all their sets belong together.
    twice = signed.filter("doc_id is not null").groupBy("doc_id").agg(F.min(F.xxhash64(*key)).alias("low"), F.max(F.xxhash64(*key)).alias("high")).filter("low <> high").select("doc_id")
    twice = C.settle(signed.drop("parts").join(twice, "doc_id").join(classes.select(*key, "id"), key).select("doc_id", "id").distinct(), "near-twice")
    some = twice.limit(1).count() > 0
    if some:
        hubs = twice.groupBy("doc_id").agg(F.min("id").alias("hub"))
        comp = C.joined(comp, twice.join(hubs, "doc_id").select(F.col("id").alias("a"), F.col("hub").alias("b")), "near-three")

    # A component is named by its smallest doc_id.
    of_class = classes.join(comp, "id", "left").select(*key, "id", "first_doc", F.coalesce("comp", "id").alias("comp"))
    names = of_class.groupBy("comp").agg(F.min("first_doc").alias("component"))
    of_class = C.settle(of_class.join(names, "comp").select(*key, "id", "component"), "near-components")
    on = [F.col(f"s.{c}") == F.col(f"c.{c}") for c in key]
    out = signed.select("doc_id", *key).alias("s").join(of_class.alias("c"), on, "left").select("s.doc_id", F.col("s.n_shingles").alias("n_shingles"), "c.component")
    if some:  # an empty text of such an id belongs to it too
        of_doc = twice.join(of_class.select("id", "component"), "id").groupBy("doc_id").agg(F.min("component").alias("of_doc"))
        out = out.join(of_doc, "doc_id", "left").withColumn("component", F.coalesce("of_doc", "component"))
    # A row with words but without an id has a class's component only if that class has rows with ids.
    comp_id = F.when(F.col("doc_id").isNull(), F.lit(None).cast("long")).otherwise(F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", comp_id.alias("component_id"), F.coalesce(F.col("doc_id") == comp_id, F.lit(True)).alias("kept"))


def survivors(docs: DataFrame, percent: int = 85) -> DataFrame:
    """The rows of docs, whole, that stay: one document of each group. Of rows that share a doc_id one stays; rows
    without an id all stay."""
    columns, row = docs.columns, "survivor_row"
    while row in map(str.lower, columns):
        row += "_"
    docs = C.settle(docs.withColumn(row, F.monotonically_increasing_id()), "near-rows")
    kept = near_duplicates(docs, percent).filter("kept and doc_id is not null").select("doc_id").distinct()
    chosen = docs.select("doc_id", row).join(kept, "doc_id", "left_semi").groupBy("doc_id").agg(F.min(row).alias(row))
    with_id = docs.join(chosen, row, "left_semi").select(*columns)
    return with_id.unionByName(docs.filter("doc_id is null").select(*columns))

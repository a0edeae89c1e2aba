"""The pipeline's stages against brute force, each on its own input, and run() against the chain of its stages."""

from __future__ import annotations

import re
import zlib
from functools import cache

import corpus_pipeline
import pytest
from pyspark.sql import functions as F
from test_operators import ALNUM, FOLD, SCHEMA, base_by_regex, components_by_brute_force, docs, empty, rows, words  # noqa: F401

from pathweave.llm import op2_pii, op8_language

NAMES = ["language", "near_duplicates", "decontamination", "personal_data", "packing"]


def contaminated(text, items):
    w, hit = words((text or "").translate(FOLD), ALNUM), set()
    for t in items:
        b = words((t or "").translate(FOLD), ALNUM)
        n = min(13, len(b))
        wins = {tuple(b[j : j + n]) for j in range(len(b) - n + 1)} if b else set()
        for j in range(len(w) - n + 1) if b else ():
            if tuple(w[j : j + n]) in wins:
                hit |= set(range(j, j + n))
    return bool(hit) and 20 * len(hit) >= len(w)


def plain(df):
    return [tuple(r[c] for c in ("doc_id", "text", "lang", "source", "n_chars")) for r in df.collect()]


@pytest.fixture
def folder(spark, docs, tmp_path):  # noqa: F811
    items = [(1, " ".join(f"bench{i}" for i in range(20))), (2, None), (3, "")]
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs.withColumn("survivor_row", F.lit("clash")).write.parquet(str(tmp_path / "documents.parquet"))
    return str(tmp_path)


def test_stages_and_run(spark, rows, folder, monkeypatch):  # noqa: F811
    from tokenizers import Tokenizer
    import public_tokenizers

    assert [n for n, _ in corpus_pipeline.STAGES] == NAMES
    # The same training twice would only take longer.
    train = op2_pii.train
    once = cache(lambda: train(spark.read.parquet(f"{folder}/personal.parquet").select("text")))
    monkeypatch.setattr(op2_pii, "train", lambda d, *a: once())
    given = spark.read.parquet(f"{folder}/documents.parquet")
    stage = dict(corpus_pipeline.STAGES)

    def after(name, d):
        out = stage[name](spark, d, folder)
        assert out.columns == given.columns
        out.write.parquet(f"{folder}/{name}.parquet")
        out = spark.read.parquet(f"{folder}/{name}.parquet")
        assert out.filter("survivor_row <> 'clash' or id <> 'clash'").count() == 0
        return out

    one = after("language", given)
    left = plain(one)
    model = op8_language.train(op8_language.learnable(given))
    sure = {r["doc_id"] for r in op8_language.identify(given, model).collect() if r["lang_pred"] != "und" and r["score"] >= corpus_pipeline.LEAST_SCORE}
    assert sorted(r[0] for r in left) == sorted(r[0] for r in rows if r[0] in sure)
    assert not {222, 223, 224} & sure and {r[0] for r in rows if r[0] < 220} <= sure

    two = after("near_duplicates", one)
    want = components_by_brute_force(left, 80)
    assert sorted(r[0] for r in plain(two)) == sorted(i for i, (_, c) in want.items() if i == c)
    assert not {200, 201, 202} & {r[0] for r in plain(two)}

    three = after("decontamination", two)
    bench = [r["text"] for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    assert sorted(plain(three)) == sorted(r for r in plain(two) if not contaminated(r[1], bench))
    assert 240 not in {r[0] for r in plain(three)}

    three.write.parquet(f"{folder}/personal.parquet")
    four = after("personal_data", three)
    was, now = {r[0]: r for r in plain(three)}, {r[0]: r for r in plain(four)}
    assert was.keys() == now.keys()
    for i, (_, text, lang, source, n) in now.items():
        assert (lang, source, n) == (was[i][2], was[i][3], len(text))
        assert not any(base_by_regex(text).values())
        if not re.search(r"[0-9@]", was[i][1]):
            assert text == was[i][1]

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    pieces = {}
    for i, r in now.items():
        ids = t.encode(r[1], add_special_tokens=False).ids + [0]
        for k in range(0, len(ids), 2048):
            part = ids[k : k + 2048]
            pieces[i, k // 2048] = (k, len(part), zlib.crc32(b"".join(x.to_bytes(4, "little") for x in part)))
    for made in (stage["packing"](spark, four, folder), corpus_pipeline.run(spark, folder)):
        got = made.collect()
        assert len(got) == len(pieces)
        assert {(r["doc_id"], r["piece"]): (r["start"], r["length"], r["ids_crc32"]) for r in got} == pieces
        ends = {}
        for r in sorted(got, key=lambda r: r["offset"]):
            assert ends.get(r["sequence_id"], 0) == r["offset"]
            ends[r["sequence_id"]] = r["offset"] + r["length"]
        assert max(ends.values()) <= 2048


def test_nothing_and_nulls(spark, empty, tmp_path):  # noqa: F811
    folder = str(tmp_path)
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    none = spark.createDataFrame([(None, None, None, None, None)] * 2, SCHEMA)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, folder).count() == 0, name
        n = stage(spark, none, folder).count()
        # Rows without a letter have no language; whatever has no id is its own document.
        assert n == (0 if name == "language" else 2), name
    empty.write.parquet(f"{folder}/documents.parquet")
    assert corpus_pipeline.run(spark, folder).count() == 0


def test_near_duplicates_keep_clashing_columns(spark):
    d = spark.createDataFrame([(2, "a b", "x", "y"), (1, "a b", "p", "q")], "doc_id long, text string, survivor_row string, Bucket string")
    got = corpus_pipeline.near_duplicates(spark, d, "")
    assert got.columns == d.columns and [tuple(r) for r in got.collect()] == [(1, "a b", "p", "q")]

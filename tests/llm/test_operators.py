"""Each training-data operator against a brute-force reading of its contract, on a small fixture with awkward rows."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

from pathweave.llm import common as C
from pathweave.llm import (
    op1_decontaminate, op2_pii, op3_minhash, op4_quality, op5_hosts, op6_packing, op7_tools, op8_language, op9_substring, op10_license,
)

FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def sha(x: str) -> str:
    return hashlib.sha256(x.encode()).hexdigest()


@pytest.fixture(scope="module")
def rows():
    r = random.Random(4)
    vocabulary = {"en": ["the", "of", "and", "house", "water", "Éa", "river", "stone"] + [f"en{i}x" for i in range(300)], "de": ["der", "die", "und", "haus", "wäßrig", "fluß"] + [f"de{i}ü" for i in range(300)]}
    out = []
    for i in range(120):
        lang = "en" if i % 3 else "de"
        text = "\n".join(" ".join(r.choice(vocabulary[lang]) for _ in range(r.randint(20, 60))) for _ in range(r.randint(1, 5)))
        out.append((i, text, lang, f"s{i % 3}", len(text)))
    copy = lambda i, j, f=lambda t: t: out.append((i, f(out[j][1]), out[j][2], out[j][3], 0))
    copy(200, 5), copy(201, 5), copy(202, 7, lambda t: t + " extra"), copy(203, 202 - 200 + 8, str.upper)
    passage = " ".join(f"pass{i}" for i in range(60))
    for i, j in ((210, 11), (211, 12), (212, 13)):
        w = out[j][1].split(" ")
        out.append((i, " ".join([*w[:10], passage, *w[10:]]), "en", "s0", 0))
    pii = "mail a.b@mail.example.com or c@d.e, host 10.1.2.3 and 300.1.1.1, card 4465 7583 8288 9437, call +1 (743) 555-3824 now"
    out += [(220, pii, "en", "s1", 0), (221, "x " * 30000, "en", "s1", 0), (222, "", "en", None, 0), (223, None, None, "s2", None), (224, "12 ++ 34", None, "s2", 0), (225, "one two", "en", "s2", 0)]
    out += [(230, "Released under the MIT License. " + out[3][1] + " Licensed under the Apache License, Version 2.0. CC BY-NC", "en", "s1", 0), (231, "under the mit license cc by nc cc by nc", "en", "s1", 0)]
    out += [(240, out[20][1] + " " + " ".join(f"bench{i}" for i in range(20)), "en", "s2", 0), (5, out[5][1], out[5][2], out[5][3], 0)]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).withColumn("id", F.lit("clash")).withColumn("row", F.lit("clash")).withColumn("n", F.lit(1)).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text, sep=r"[\x20\x09-\x0D]+"):
    return [w for w in re.split(sep, text or "") if w]


ALNUM = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


# ------------------------------------------------------------------ 1
@pytest.mark.parametrize("block_bytes", [1 << 20, 200])
def test_decontamination(spark, docs, rows, empty, block_bytes):
    items = [(1, " ".join(f"bench{i}" for i in range(20))), (2, "one TWO"), (3, None), (4, " ".join(words(rows[30][1], ALNUM)[3:30])), (10, "one two"), (None, "one two")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in op1_decontaminate.report(op1_decontaminate.scan(docs, bench, block_bytes=block_bytes)).collect()}
    want = set()
    for i, text, *_ in rows:
        w = words((text or "").translate(FOLD), ALNUM)
        hit, found = set(), set()
        for item, t in items:
            b = words((t or "").translate(FOLD), ALNUM)
            n = min(13, len(b))
            wins = {tuple(b[j : j + n]) for j in range(len(b) - n + 1)} if b else set()
            for j in range(len(w) - n + 1) if b else ():
                if tuple(w[j : j + n]) in wins:
                    hit |= set(range(j, j + n))
                    if item is not None:
                        found.add(str(item))
        want.add((i, len(w), len(hit), len(found), sha(",".join(sorted(found))), len(hit) > 0 and 20 * len(hit) >= len(w)))
    assert got == want
    assert op1_decontaminate.report(op1_decontaminate.scan(empty, bench)).count() == 0
    assert {r["doc_id"] for r in op1_decontaminate.clean(docs, bench).collect()} == {i for i, *_, bad in want if not bad}


def test_decontamination_offsets(spark):
    d = spark.createDataFrame([(1, "É! Alpha-beta, GAMMA end")], "doc_id long, text string")
    b = spark.createDataFrame([(7, "alpha beta gamma")], "item_id long, text string")
    (r,) = op1_decontaminate.scan(d, b).collect()
    a, z = r["spans"]
    assert "É! Alpha-beta, GAMMA end"[a:z] == "Alpha-beta, GAMMA"


# ------------------------------------------------------------------ 2
def base_by_regex(text):
    out = {k: [] for k in op2_pii.KINDS}
    out["email"] = [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out["ip"] = [m.span() for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub("[^0-9]", "", m[0])
        if 16 <= len(d) <= 19 and op2_pii.luhn(d):
            out["card"].append(m.span())
    out["phone"] = [m.span() for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return out


def test_fixed_patterns_match_the_regexes():
    r = random.Random(2)
    letters = "ab1234.@-+ (%_é\n"
    for _ in range(4000):
        t = "".join(r.choice(letters) for _ in range(r.randint(0, 40)))
        assert op2_pii.base_spans(t) == (base_by_regex(t) if re.search("[0-9@]", t) else {k: [] for k in op2_pii.KINDS}), t


def test_personal_data(spark, docs, rows, empty):
    got = {r["doc_id"]: r for r in op2_pii.personal_data(docs).collect()}
    for i, text, *_ in rows:
        found = base_by_regex(text or "")
        base = [f"{k}:{s}:{e}" for k in op2_pii.KINDS for s, e in found[k]]
        r = got[i]
        assert (r["n_email"], r["n_ip"], r["n_card"], r["n_phone"]) == tuple(len(found[k]) for k in op2_pii.KINDS)
        assert r["base_sha256"] == sha(",".join(base))
        assert set(base) <= set(r["spans"].split(",")) or not base
    assert got[220]["n_email"] == 2 and got[220]["n_ip"] == 1 and got[220]["n_card"] == 1 and got[220]["n_phone"] == 1
    assert op2_pii.personal_data(empty).count() == 0
    shown = {r["doc_id"]: r["text"] for r in op2_pii.masked(docs).select("doc_id", "text").collect()}
    assert "<email>" in shown[220] and "<phone>" in shown[220] and "@" not in shown[220]
    assert shown[223] is None and shown[1] == rows[1][1]


def test_overlapping_spans_are_masked_whole(spark):
    texts = ["to +14155550100@carrier.com now", "to 10.1.2.3@host.org now", "to 4465758382889437@card.example.org now"]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["text"] for r in op2_pii.masked(d).collect()} == {"to <email> now"}


def test_copies_count_once_in_training(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(op2_pii, "training_windows", lambda texts: seen.extend(texts))
    d = spark.createDataFrame([(f"mail a{i}@host.example.org",) for i in range(8) for _ in range(10)], "text string")
    op2_pii.train(d, sample_docs=5)
    assert len(seen) == len(set(seen)) == 5


def test_tagger_learns_and_windows_agree():
    r = random.Random(5)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7)))
    texts = []
    for i in range(160):
        n = "".join(str(r.randint(0, 9)) for _ in range(10))
        span = [f"+1 ({n[:3]}) {n[3:6]}-{n[6:]}", f"{word()}@{word()}.com", f"{r.randint(1, 255)}.{r.randint(0, 255)}.{r.randint(0, 255)}.{r.randint(0, 255)}"][i % 3]
        texts.append(" ".join(word() for _ in range(20)) + f" {span} " + " ".join(word() for _ in range(20)))
    tagger = op2_pii.Tagger().fit(op2_pii.training_windows(texts[:120], most=1600), epochs=12)
    found = op2_pii.read_spans(texts[120:], tagger)
    want = [{(k, s, e) for k, v in op2_pii.base_spans(t).items() for s, e in v} for t in texts[120:]]
    assert sum(bool(set(f) & w) for f, w in zip(found, want)) >= 0.7 * len(want)
    assert op2_pii.read_spans(["no marks at all " * 50], tagger) == [[]]


def test_gradients_of_the_tagger():
    """Against finite differences of the loss, for every parameter."""
    import numpy as np

    t = op2_pii.Tagger()
    r = np.random.default_rng(0)
    t.p = {k: (v + 0.3 * r.standard_normal(v.shape)).astype(np.float32) for k, v in t.p.items()}
    x, y = r.integers(97, 110, (8, 3)), np.zeros((8, 3), int)
    y[3:6, 1], y[0:3, 2] = [1, 2, 2], [5, 6, 6]
    g = t.gradients(x, y)
    for k, v in t.p.items():
        flat = np.argsort(-np.abs(g[k]).reshape(-1))[:3]
        for i in flat:
            at, keep = np.unravel_index(i, v.shape), v[np.unravel_index(i, v.shape)]
            sides = []
            for e in (2e-2, -2e-2):
                v[at] = keep + e
                sides.append(t.loss(x, y))
            v[at] = keep
            assert abs((sides[0] - sides[1]) / 4e-2 - g[k][at]) < 0.03 * max(1.0, abs(g[k][at])), (k, at)


def test_the_tagger_finds_altered_forms_that_it_was_not_trained_on():
    """Precision and recall by kind on forms in texts that the training didn't see; and nothing in texts without any."""
    import numpy as np

    r = random.Random(7)
    word = lambda: "".join(r.choice("abcdefghinorst") for _ in range(r.randint(2, 8)))
    digits = lambda n: "".join(str(r.randint(0, 9)) for _ in range(n))
    own = {
        "phone": lambda: f"+1 ({r.randint(2, 9)}{digits(2)}) {digits(3)}-{digits(4)}", "email": lambda: f"{word()}.{word()}@{word()}.{r.choice(['com', 'org', 'net'])}",
        "ip": lambda: ".".join(str(r.randint(0, 255)) for _ in range(4)), "card": lambda: op2_pii._grouped(op2_pii._luhn_digits(16, np.random.default_rng(r.randint(0, 10**6))), " "),
    }
    text = lambda span: " ".join(word() for _ in range(25)) + f" {span} " + " ".join(word() for _ in range(25))
    tagger = op2_pii.Tagger().fit(op2_pii.training_windows([text(own[k]()) for k in own for _ in range(40)], most=2000), epochs=12)
    rnd, found, all_, extra = np.random.default_rng(123), {}, {}, 0
    for k in own:
        for _ in range(12):
            for form in op2_pii.altered(k, own[k](), rnd):
                t = text(form)
                at = t.index(form)
                got = op2_pii.read_spans([t], tagger)[0]
                found[k], all_[k] = found.get(k, 0) + ((k, at, at + len(form)) in got), all_.get(k, 0) + 1
                extra += sum(x[1] >= at + len(form) or x[2] <= at for x in got)
    recall = {k: found[k] / all_[k] for k in own}
    assert min(recall.values()) >= 0.5 and sum(found.values()) >= 0.65 * sum(all_.values()), recall
    assert extra <= 0.02 * sum(all_.values())
    clean = [text(x) for x in ("12", "1999", "v2.3", "2024-01-05", "7%", "@")]
    assert op2_pii.read_spans(clean, tagger) == [[]] * 6


def test_windows_join_in_one_legal_sequence():
    """A span over the seam of two windows is one span; every inside follows its begin."""
    import numpy as np

    t = op2_pii.Tagger()
    r = np.random.default_rng(4)
    tags, _ = t.decode(r.standard_normal((300, 5, op2_pii.TAGS)).astype(np.float32) * 3)
    ok = op2_pii.allowed()
    assert all(ok[a, b] for col in tags.T for a, b in zip(col, col[1:])) and not (tags[0] % 2 == 0)[tags[0] > 0].any()
    text = "x" * 90 + " 1 " + "y" * 400 + " 2"
    picked = op2_pii.windows_of(text)
    assert (np.diff(picked) >= 1).all() and all(any(k * op2_pii.STRIDE <= m < k * op2_pii.STRIDE + op2_pii.WINDOW for k in picked) for m in (91, len(text) - 1))


# ------------------------------------------------------------------ 3
def components_by_brute_force(rows, percent, k=5):
    sets = {}
    for i, text, *_ in rows:
        w = words((text or "").translate(FOLD))
        sets[i] = {tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))} if w else set()
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                    x, y = sorted((find(a), find(b)))
                    up[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("small_bucket", [12, 1])
def test_near_duplicates(docs, rows, empty, small_bucket):
    got = op3_minhash.near_duplicates(docs, small_bucket=small_bucket).collect()
    want = components_by_brute_force(rows, 85)
    assert len(got) == len(rows)
    assert {(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in got} == {(i, n, c, i == c) for i, (n, c) in want.items()}
    assert op3_minhash.near_duplicates(empty).count() == 0


def test_one_row_of_each_survivor_stays(spark, docs, rows):
    want = components_by_brute_force(rows, 85)
    got = op3_minhash.survivors(docs)
    assert got.columns == docs.columns
    assert sorted(r["doc_id"] for r in got.collect()) == sorted(i for i, (_, c) in want.items() if i == c)
    lone = spark.createDataFrame([(None, "a"), (None, "a"), (1, "b"), (1, "b")], "doc_id long, text string")
    assert sorted(r["text"] for r in op3_minhash.survivors(lone).collect()) == ["a", "a", "b"]


def test_near_duplicates_of_a_crowd(spark):
    """Many sets around one core, linked in chains and not: buckets mix components."""
    r = random.Random(9)
    core = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(150):
        w = list(core)
        for _ in range(i % 7):
            w[r.randrange(120)] = f"x{r.randrange(60)}"
        rows.append((i, " ".join(w)))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    want = {i: c for i, (_, c) in components_by_brute_force(rows, 85).items()}
    for small in (12, 2):
        assert {r["doc_id"]: r["component_id"] for r in op3_minhash.near_duplicates(d, small_bucket=small).collect()} == want


def test_components_of_long_chains(spark):
    """Chains of several hundred, in random and in descending order, and a lone pair."""
    order = list(range(1, 400))
    random.Random(6).shuffle(order)
    chains = [[1000, *(1000 + i for i in order)], [2000, *range(2299, 2000, -1)], [3001, 3000]]
    links = spark.createDataFrame([x for c in chains for x in zip(c, c[1:])], "a long, b long")
    got = {r["id"]: r["comp"] for r in C.components(links, "test").collect()}
    assert got == {i: min(c) for c in chains for i in c}


# ------------------------------------------------------------------ 4
def test_quality(spark, docs, rows, empty):
    boiler = "this very same line stands in every page of the host"
    more = [(1000 + i, f"{boiler}\nsome{i} own{i} words{i}", "en", "s9", 0) for i in range(60)]
    d = docs.select("doc_id", "text", "source").union(spark.createDataFrame(more, SCHEMA).select("doc_id", "text", "source"))
    got = {r["doc_id"]: r for r in op4_quality.judged(d).collect()}
    for i, text, *_ in [*rows, *more]:
        w = words(text)
        lines = [x for x in (text or "").split("\n") if words(x)]
        grams = Counter(tuple(w[j : j + 3]) for j in range(len(w) - 2))
        again = {p for j in range(len(w) - 2) if grams[tuple(w[j : j + 3])] > 1 for p in (j, j + 1, j + 2)}
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(again))
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want, i
        assert r["base_failed"] == (want[0] < 50 or 100 * want[4] > 50 * want[0])
    assert got[1000]["n_removed_words"] == 14 and not got[1]["n_removed_words"]
    assert op4_quality.judged(empty).count() == 0
    long = spark.createDataFrame([(i, f"{' '.join(f'a{j}' for j in range(60))}\nw{'x' * i}", "h") for i in range(50)] + [(99, " ".join(f"b{j}" for j in range(60)), "h")], "doc_id long, text string, source string")
    kept = {r["doc_id"]: r["kept"] for r in op4_quality.judged(long).collect()}
    assert kept[99] and not any(kept[i] for i in range(50))
    text = {r["doc_id"]: r["text"] for r in op4_quality.cleaned(long).collect()}
    assert text[3] == "wxxx" and text[99].startswith("b0")


# ------------------------------------------------------------------ 5
def test_hosts(spark):
    urls = ["http://A.example.org/en/12?x", "https://example.org/es/a", "ftp://b.com/fr/1", "https://q.com/de/#f", "no url", None, "https://good.net/1", "https://BAD.net/2", "x://notorg/"]
    urls += ["https://bad.net/p"] * 20 + ["https://good.net/p"] * 20
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("host", F.lit("clash"))
    labels = spark.createDataFrame([(i, int("bad" in (u or "").lower())) for i, u in enumerate(urls) if i > 5] + [(None, 1), (3, None)], "page_id long, bad int")
    got = {r["page_id"]: r for r in op5_hosts.filtered(pages, labels).collect()}
    assert len(got) == len(urls)
    assert [(got[i]["host"], got[i]["path"], got[i]["rule"]) for i in range(9)] == [
        ("a.example.org", "/en/12", "example.org/en/1"), ("example.org", "/es/a", "example.org/es/"), ("b.com", "/fr/1", "com/fr/"), ("q.com", "/de/", "com/de/"), ("", "", None), ("", "", None), ("good.net", "/1", None), ("bad.net", "/2", None), ("notorg", "/", None),
    ]
    assert [got[i]["verdict"] for i in (0, 1, 2, 3, 6, 7)] == ["block", "block", "allow", "block", "allow", "block"]
    none = op5_hosts.filtered(pages, labels.filter("false")).collect()
    assert {r["verdict"] for r in none if r["rule"] is None} == {"allow"}


# ------------------------------------------------------------------ 6
def test_packing(docs, rows, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    ids = {i: t.encode(text or "", add_special_tokens=False).ids + [0] for i, text, *_ in rows}
    got = op6_packing.pack(docs, with_ids=True).collect()
    back: dict = {}
    for r in got:
        part = ids[r["doc_id"]][r["start"] : r["start"] + 2048]
        assert r["ids"] == part and r["length"] == len(part) and r["start"] == 2048 * r["piece"]
        assert r["ids_crc32"] == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in part))
        back.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert Counter(r["doc_id"] for r in got) == Counter(i for i, *_ in rows for _ in range(-(-len(ids[i]) // 2048)))
    for v in back.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 2048
    total = sum(len(ids[i]) for i, *_ in rows)
    assert len(back) <= -(-total // 2048) + 2
    assert op6_packing.pack(empty).count() == 0


def test_plan_packs_all_and_fills_gaps():
    r = random.Random(1)
    for _ in range(30):
        h = Counter(r.randint(1, 100) for _ in range(r.randint(1, 400)))
        planned = op6_packing.plan(dict(h), 100)
        used: Counter = Counter()
        for lengths, times in planned:
            assert sum(lengths) <= 100 and times > 0
            for n in lengths:
                used[n] += times
        assert used == h
    assert sum(t for _, t in op6_packing.plan({60: 5, 40: 5}, 100)) == 5
    assert sum(t for _, t in op6_packing.plan({50: 3, 30: 3, 20: 3}, 100)) == 3


# ------------------------------------------------------------------ 7
def test_tool_calls(spark):
    calls = spark.createDataFrame(
        [("a", 1, 0, "reply", '{"words": 2, "text": "hi"}', []), ("b", 1, 2, "reply", '{"text": "$ref:a", "words": "x"}', ["a"]), ("c", 1, 4, "other", "not json", ["b", "zz"]), (None, 1, 5, "reply", None, []), ("d", 2, 0, "reply", "{}", ["e"]), ("e", 2, 1, "reply", "{}", ["d"])],
        "id string, conv_id long, turn long, name string, arguments string, refs array<string>",
    )
    results = spark.createDataFrame([("a", 1, 1, 'say "x"'), ("b", 1, 3, None), ("b", 1, 3, "again"), ("lost", 1, 9, "?"), (None, 1, 9, "?")], "id string, conv_id long, turn long, content string")
    got = op7_tools.linked(calls, results).collect()
    by = {(r["call_id"], r["result_turn"], r["turn"]): r for r in got}
    assert len(got) == 9
    assert [by["a", 1, 0]["level"], by["b", 3, 2]["level"], by["c", None, 4]["level"], by["d", None, 0]["level"]] == [0, 1, 2, None]
    assert by["a", 1, 0]["json"] == '{"arguments":{"text":"hi","words":2},"id":"a","name":"reply","result":"say \\"x\\""}'
    assert by["a", 1, 0]["valid"] and not by["b", 3, 2]["valid"] and not by["c", None, 4]["valid"]
    assert not by["c", None, 4]["linked"] and not by["lost", 9, None]["linked"]
    m = spark.createDataFrame([(1, 0, "user", "q"), (1, 1, "assistant", '{"tool_calls": [{"id": "k", "name": "reply", "arguments": "{\\"text\\":\\"$ref:j\\"}"}]}'), (1, 2, "tool", '{"tool_call_id": "k", "content": "v"}')], "conv_id long, turn long, role string, text string")
    c, r = op7_tools.from_messages(m)
    assert [(x["id"], x["refs"]) for x in c.collect()] == [("k", ["j"])] and [x["content"] for x in r.collect()] == ["v"]
    assert op7_tools.linked(calls.filter("false"), results.filter("false")).count() == 0


# ------------------------------------------------------------------ 8
def test_language(docs, rows, empty):
    got = {r["doc_id"]: r for r in op8_language.languages(docs).collect()}
    for i, text, lang, *_ in rows:
        assert got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1)
        if not re.search(r"[^\W\d_]", text or ""):
            assert (got[i]["lang_pred"], got[i]["score"]) == ("und", 0.0)
        assert 0 <= got[i]["score"] <= 1
    held = [i for i, text, lang, *_ in rows if got[i]["held_out"] and lang and i < 200]
    assert sum(got[i]["lang_pred"] == next(r[2] for r in rows if r[0] == i) for i in held) >= 0.95 * len(held)
    assert op8_language.languages(empty).count() == 0
    model = op8_language.train(docs)
    assert {r["doc_id"] for r in op8_language.accepted(docs, model, 0.0).collect()} == {i for i, text, *_ in rows if re.search(r"[^\W\d_]", text or "")}


# ------------------------------------------------------------------ 9
def test_repeated_passages(docs, rows, empty):
    got = op9_substring.repeated_passages(docs).collect()
    by: dict = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append(r)
    texts = {i: t for i, t, *_ in rows}
    assert {210, 211, 212} <= by.keys()
    assert all(len(words(texts[i])) < 50 or i in by for i in (5, 200, 201))
    for i in (210, 211, 212):
        assert any("pass20" in texts[i][r["start"] : r["end"]] for r in by[i])
    clean = {i for i in range(120)} - {5, 7, 10, 11, 12, 13, 3, 20}
    assert not clean & by.keys()
    assert not [r for r in by[210] if "pass20" in texts[210][r["start"] : r["end"]] and r["removed"]]
    assert all(r["removed"] for r in by[211] if "pass20" in texts[211][r["start"] : r["end"]])
    assert op9_substring.repeated_passages(empty).count() == 0


def test_a_pasted_passage_is_found_wherever_it_stands(spark):
    r = random.Random(3)
    passage = [f"p{i}" for i in range(51)]
    rows = []
    for i in range(40):
        own = [f"d{i}w{j}" for j in range(r.randint(0, 80))]
        at = r.randint(0, len(own))
        rows.append((i, " ".join([*own[:at], *passage, *own[at:]])))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    assert {x["doc_id"] for x in op9_substring.repeated_passages(d).collect()} == set(range(40))


def removed_words(spark, rows):
    """doc_id -> for each word whether it is in a removed passage; passages of a document don't overlap."""
    texts = dict(rows)
    out = {i: [False] * len(words(t)) for i, t in rows}
    seen = set()
    for x in op9_substring.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        text = texts[x["doc_id"]]
        part = text[x["start"] : x["end"]]
        assert part == part.strip() and len(words(part)) == x["n_words"]
        a = len(words(text[: x["start"]]))
        for k in range(a, a + x["n_words"]):
            assert (x["doc_id"], k) not in seen
            seen.add((x["doc_id"], k))
            out[x["doc_id"]][k] = x["removed"]
    return out


def test_each_repeated_range_has_its_own_verdict(spark):
    """An original, an edited copy and a copy of the edit; adjacent paragraphs with different first documents."""
    one = [f"a{i}" for i in range(300)]
    two = [*one[:150], *(f"b{i}" for i in range(200))]
    near = [*one[:150], "edited", *one[151:]]
    line = lambda p: " ".join(f"{p}{i}" for i in range(40))
    rows = [(1, " ".join(one)), (2, " ".join(two)), (3, " ".join(two)), (4, " ".join(near)), (5, " ".join(near))]
    rows += [(11, line("x")), (12, "\n".join([line("y"), line("x")])), (13, "\n".join([line("x"), line("y"), line("z")])), (14, line("z"))]
    got = removed_words(spark, rows)
    assert not any(got[1]) and not any(got[11])
    assert all(got[2][20:130]) and not any(got[2][150:])
    assert all(got[3]) and all(got[4]) and all(got[5])
    assert got[12] == [False] * 40 + [True] * 40
    assert got[13] == [True] * 80 + [False] * 40
    assert all(got[14])


def test_a_pasted_passage_is_returned_whole(spark):
    """Passages of 51 and 60 words, in a line or as short lines: start, end and words are exact."""
    r = random.Random(8)
    rows, where = [], {}
    for p, (n, sep) in enumerate(((51, " "), (60, " "), (51, "\n"))):
        passage = " ".join(f"p{p}x{i}" + (sep if i % 6 == 5 and i + 1 < n else "") for i in range(n))
        for k in range(6):
            i = 10 * p + k
            head, tail = " ".join(f"é{i}h{j}" for j in range(r.randint(0, 40))), " ".join(f"d{i}t{j}" for j in range(r.randint(0, 40)))
            text = " ".join(x for x in (head, passage, tail) if x)
            rows.append((i, text))
            where[i] = (text.index(passage), text.index(passage) + len(passage), n, 10 * p, k > 0)
    d = spark.createDataFrame([*rows, rows[0]], "doc_id long, text string")
    got = [tuple(x) for x in op9_substring.repeated_passages(d).collect()]
    assert sorted(got) == sorted([(i, *v) for i, v in where.items()] + [(0, *where[0])])


def test_near_copies_of_hard_wrapped_passages(spark):
    """56 words in lines of 8, one of them changed: alone and between blank lines."""
    wrap = lambda w: "\n".join(" ".join(w[i : i + 8]) for i in range(0, len(w), 8))
    rows = []
    for p in range(12):
        one = [f"p{p}w{i}" for i in range(56)]
        two = [*one[:28], "changed", *one[29:]]
        other = lambda k: wrap([f"o{p}{k}v{i}" for i in range(24)])
        rows.append((10 * p, wrap(one)))
        rows.append((10 * p + 1, [wrap(two), f"{other(1)}\n\n{wrap(two)}\n \n{other(2)}"][p % 2]))
    got = removed_words(spark, rows)
    for p in range(12):
        assert not any(got[10 * p])
        at = 24 if p % 2 else 0
        assert all(got[10 * p + 1][at : at + 56]), p
    assert max(sum(x) for x in got.values()) == 56


# ------------------------------------------------------------------ 10
def test_licenses(docs, rows, empty):
    got = {r["doc_id"]: r for r in op10_license.scan(docs).collect()}
    for i, text, *_ in rows:
        w = words((text or "").translate(FOLD), ALNUM)
        at = [(j, label) for p, label in op10_license.PHRASES for q in [p.split()] for j in range(len(w)) if w[j : j + len(q)] == q]
        r = got[i]
        assert (r["n_words"], r["n_base"]) == (len(w), len(at)), i
        assert (r["first_word"], r["last_word"]) == ((min(at)[0], max(at)[0]) if at else (None, None)), i
        assert r["base_labels"] == ",".join(sorted({x for _, x in at}))
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1
    assert got[1]["labels"] == "" and got[1]["score"] == 0
    assert op10_license.scan(empty).count() == 0


def test_licence_votes_survive_edits(spark):
    notice = next(t for label, t in op10_license.TEMPLATES if label == "bsd")
    w = notice.split()
    w[9:9] = ["really"]
    d = spark.createDataFrame([(1, "before it " + " ".join(w) + " and after"), (2, "redistribution and use in source")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in op10_license.scan(d).collect()}
    assert got[1]["labels"] == "bsd" and 0.6 <= got[1]["score"] < 1 and got[2]["labels"] == ""


def test_levels_of_calls_with_several_references(spark):
    calls = spark.createDataFrame([("x", []), ("y", ["x"]), ("z", ["x", "y"]), ("w", ["z", "x"]), ("v", ["v", "x"])], "id string, refs array<string>")
    assert {r["id"]: r["level"] for r in op7_tools.levels(calls).collect()} == {"x": 0, "y": 1, "z": 2, "w": 3}


def test_ids_with_two_texts_carry_the_links_of_both(spark):
    a, b = " ".join(f"a{i}" for i in range(80)), " ".join(f"b{i}" for i in range(80))
    docs = spark.createDataFrame([(5, a), (5, b), (5, ""), (7, b), (3, b + " zz"), (9, None), (None, a)], "doc_id long, text string")
    got = sorted((r["doc_id"] or -1, r["n_shingles"], r["component_id"], r["kept"]) for r in op3_minhash.near_duplicates(docs).collect())
    assert got == [(-1, 76, None, True), (3, 77, 3, True), (5, 0, 3, False), (5, 76, 3, False), (5, 76, 3, False), (7, 76, 3, False), (9, 0, 9, True)]


def test_parity_bits_bound_the_difference():
    import numpy as np

    r = np.random.default_rng(1)
    for size in (1, 40, 150, 3000):
        x = r.integers(1, 2**63, size, dtype=np.uint64)
        y = np.concatenate([x[size // 10 :], r.integers(1, 2**63, size // 8, dtype=np.uint64)])
        differ = sum(bin(int(a ^ b) & (2**64 - 1)).count("1") for a, b in zip(C.parity_bits(x), C.parity_bits(y)))
        assert differ <= len(set(x.tolist()) ^ set(y.tolist()))


@pytest.mark.parametrize("block_bytes", [200, 1 << 24])
def test_many_blocks_give_what_one_gives(spark, block_bytes):
    """More blocks than a worker holds, each made once for a batch of texts."""
    bench = spark.createDataFrame([(f"b{i}", " ".join(f"w{i}x{j}" for j in range(20))) for i in range(12)], "item_id string, text string")
    docs = spark.createDataFrame([(i, " ".join(f"w{i % 14}x{j}" for j in range(3, 18)) + " more words") for i in range(400)] + [(400, None), (401, "")], "doc_id long, text string")
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"]) for r in op1_decontaminate.report(op1_decontaminate.scan(docs, bench, block_bytes=block_bytes)).collect()}
    assert got == {**{i: (17, 15 if i % 14 < 12 else 0, int(i % 14 < 12)) for i in range(400)}, 400: (0, 0, 0), 401: (0, 0, 0)}


def test_beta_quantiles():
    import numpy as np

    a, b = np.array([1.0, 2.0, 0.5, 30.0, 3.0]), np.array([1.0, 1.0, 0.5, 70.0, 200.0])
    x = op5_hosts.beta_quantile(a, b)
    # Closed forms: x, x^2, the arcsine law.
    assert np.allclose(x[:3], [0.05, 0.05**0.5, np.sin(np.pi * 0.05 / 2) ** 2], atol=1e-9)
    r = np.random.default_rng(3)
    for i in (3, 4):
        assert abs((r.beta(a[i], b[i], 400_000) < x[i]).mean() - 0.05) < 0.002


def test_host_reputation_against_the_formulas(spark):
    import numpy as np

    names = ["a.x.co.uk", "b.x.co.uk", "y.co.uk", "user@z.net:80", "10.0.0.1", "q.net", "lone"]
    got = spark.createDataFrame([(n,) for n in names], "h string").select("h", op5_hosts.domain_of(F.col("h")).alias("d"), op5_hosts.suffix_of(F.col("h")).alias("s")).collect()
    assert [(r["d"], r["s"]) for r in got] == [("x.co.uk", "co.uk"), ("x.co.uk", "co.uk"), ("y.co.uk", "co.uk"), ("z.net", "net"), ("10.0.0.1", "10.0.0.1"), ("q.net", "net"), ("lone", "lone")]
    bad = {"bad.net": 1.0, "good.net": 0.0, "mixed.net": 0.5}
    pages = [(i, f"http://{h}/{i}") for i, h in enumerate(h for h in bad for _ in range(40))] + [(200, "http://new.bad.net/"), (201, None), (202, "nothing")]
    labels = [(i, int((i % 40) < 40 * bad[p[1].split("/")[2]])) for i, p in enumerate(pages[:120])]
    out = {r["page_id"]: r for r in op5_hosts.filtered(spark.createDataFrame(pages, "page_id long, url string").withColumn("host", F.lit("clash")), spark.createDataFrame(labels, "page_id long, bad int")).collect()}
    assert out[0]["verdict"] == "block" and out[200]["verdict"] == "block" and out[50]["verdict"] == "allow" and out[100]["verdict"] == "allow" and out[201]["verdict"] == "allow" and out[202]["host"] == ""

    def fitted(n, y, prior):
        s, c, p = ((y - n * prior) ** 2).sum(), (n * prior * (1 - prior)).sum(), (n * (n - 1) * prior * (1 - prior)).sum()
        rho = (s - c) / p if p > 0 and s > c else 0.0
        return round(max(2.0, min(200.0, 1 / rho - 1 if rho > 0 else 200.0)), 6)

    all_mean = (60 + 1) / (120 + 2)
    n, y = np.array([120.0]), np.array([60.0])
    size = fitted(n, y, all_mean)
    suffix = (all_mean * size + 60) / (size + 120)
    n, y = np.array([40.0] * 3), np.array([40.0, 0.0, 20.0])
    size = fitted(n, y, suffix)
    domain = (suffix * size + y) / (size + n)
    size2 = round(max(2.0, min(200.0, (lambda s, c, p: 1 / ((s - c) / p) - 1 if p > 0 and s > c else 200.0)(((y - n * domain) ** 2).sum(), (n * domain * (1 - domain)).sum(), (n * (n - 1) * domain * (1 - domain)).sum()))), 6)
    want = op5_hosts.beta_quantile(domain * size2 + y, (1 - domain) * size2 + n - y)
    assert np.allclose([out[0]["bound"], out[40]["bound"], out[80]["bound"]], want, atol=1e-6)
    none = op5_hosts.filtered(spark.createDataFrame([], "page_id long, url string"), spark.createDataFrame([], "page_id long, bad int"))
    assert none.count() == 0


def test_a_template_position_counts_once(spark):
    """Hits of one part of a template, again and again, are no cover of the whole."""
    notice = "permission is hereby granted free of charge"
    docs = spark.createDataFrame([(1, " ".join([notice] * 40)), (2, op10_license.TEMPLATES[1][1]), (3, "x " + op10_license.TEMPLATES[1][1].replace("without limitation", "with no limit")), (None, notice), (4, None)], "doc_id long, text string")
    got = {r["doc_id"]: (r["labels"], r["vote_score"]) for r in op10_license.scan(docs).collect()}
    assert got[1] == ("", 0.0) and got[2] == ("mit", 1.0) and got[3][0] == "mit" and 0.6 <= got[3][1] < 1 and got[4] == ("", 0.0) and got[None] == ("", 0.0)

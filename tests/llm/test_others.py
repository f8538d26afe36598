import hashlib
import math
import random

import pytest

from hazemedian.llm.mixing import bisect_alpha, entropy, epochs, mixed, plan, schedule, weights_at
from hazemedian.llm.syncmers import fingerprints
from hazemedian.llm.tiling import contaminated_pairs, tiles, tokens_of

from .conftest import HARD

BENCH = "item_id long, text string"


def test_tiling_catches_reordered_passages(spark, frame, words):
    item = words(60, 1).split()
    moved = " ".join(item[30:] + ["between"] + item[:30])
    rows = [(1, words(50, 2) + " " + " ".join(item) + " " + words(40, 3)), (2, words(100, 4) + " " + moved.upper() + "!"), (3, words(300, 5)), (4, words(20, 6) + " " + " ".join(item[:20])), (5, " ".join(item[:35])), *((100 + d, t) for d, t in HARD)]
    bench = spark.createDataFrame([(7, " ".join(item)), (8, None), (9, ""), (10, "tiny item"), (None, "x")], BENCH)
    got = {(r["doc_id"], r["item_id"]): r for r in contaminated_pairs(frame(rows), bench).collect()}
    assert got.keys() == {(1, 7), (2, 7), (5, 7)}
    assert got[1, 7]["coverage"] == 1 and got[2, 7]["n_tiles"] == 2 and got[2, 7]["tiled_tokens"] == 60
    assert contaminated_pairs(frame([(1, "a tiny, ITEM. here")]), bench).first()["item_id"] == 10
    assert contaminated_pairs(frame([]), bench).count() == 0 and contaminated_pairs(frame(rows), bench.limit(0)).count() == 0


def test_blocks_change_nothing(spark, frame, words, monkeypatch):
    from hazemedian.llm import tiling

    bench = spark.createDataFrame([(k, words(30, k)) for k in range(20)], BENCH)
    df = frame([(k, words(40, 100 + k) + " " + words(30, k % 25)) for k in range(60)])
    whole = sorted(map(tuple, contaminated_pairs(df, bench).collect()))
    monkeypatch.setattr(tiling, "BLOCK_BYTES", 700)
    assert sorted(map(tuple, contaminated_pairs(df, bench).collect())) == whole and len(whole) == 50


def brute_tiles(doc, item, match):
    """Greedy tiling straight from its definition: longest first, then first in the item, then in the document."""
    used_d, used_i, total = set(), set(), []
    while True:
        best = None
        for j in range(len(item)):
            for i in range(len(doc)):
                n = 0
                while i + n < len(doc) and j + n < len(item) and doc[i + n] == item[j + n] and i + n not in used_d and j + n not in used_i:
                    n += 1
                if n >= match and (best is None or n > best[0]):
                    best = n, j, i
        if best is None:
            return total
        n, j, i = best
        used_d |= set(range(i, i + n))
        used_i |= set(range(j, j + n))
        total.append(best)


def test_tiles_equal_brute_force():
    import numpy as np

    for seed in range(40):
        rng = random.Random(seed)
        doc, item = ([rng.randrange(4) for _ in range(n)] for n in (60, 25))
        at = [(i, j) for i in range(58) for j in range(23) if doc[i : i + 3] == item[j : j + 3]]
        found = tiles(np.array(doc), np.array(item), np.array([x for x, _ in at], int), np.array([x for _, x in at], int), 3)
        assert sum(x[0] for x in found) == sum(x[0] for x in brute_tiles(doc, item, 3))
        assert sorted(x[0] for x in found) == sorted(x[0] for x in brute_tiles(doc, item, 3))
    assert len(tokens_of(__import__("pyarrow").array(["A-b c", None]))[0]) == 3


def edited_text(docs, k):
    ordered = sorted(docs, key=lambda x: -x[0])
    text, after = ordered[k][1] or "", ordered[(k + 1) % len(ordered)][1] or ""
    half = len(text) // 2
    return text[: len(text) - half] + after[:half]


def test_fingerprints(frame, words):
    docs = [(10 * k, words(60 + k, k)) for k in range(30)] + [(1001, words(80, 3)), (1002, words(80, 3)), (1003, "日本語のテキストです。" * 30), (1004, words(12, 5)), *((2000 + d, t) for d, t in HARD if d != 9)]
    got = {r["doc_id"]: r for r in fingerprints(frame([*docs, (None, "x")])).collect()}
    assert got.keys() == {d for d, _ in docs}
    for k, (d, t) in enumerate(sorted(docs, key=lambda x: -x[0])):
        assert got[d]["n_chars"] == len(t or "")
        assert got[d]["edited_sha256"] == hashlib.sha256(edited_text(docs, k).encode()).hexdigest()
        assert 0 <= got[d]["near_edited"] <= 1 and 0 <= got[d]["near_next"] <= 1
    assert got[1001]["fingerprint"] == got[1002]["fingerprint"] and got[1002]["near_next"] == 1 and got[1001]["near_next"] < 0.1
    assert all(got[10 * k]["near_edited"] > 0.15 > got[10 * k]["near_next"] for k in range(1, 30))
    assert got[2001]["fingerprint"] == "" and fingerprints(frame([])).count() == 0
    one = fingerprints(frame([(5, words(40, 1))])).first()
    assert one["near_next"] == 1 and one["edited_sha256"] == hashlib.sha256(edited_text([(5, words(40, 1))], 0).encode()).hexdigest()


def test_likeness_follows_one_rule_at_all_lengths(frame, words):
    for n in (60, 150, 395, 399, 401, 900):
        base = words(400, n)[:n].rsplit(" ", 1)[0]
        got = {r["doc_id"]: r for r in fingerprints(frame([(2, base), (1, base + " new")])).collect()}
        assert got[2]["near_next"] == got[1]["near_next"] > 0.6, n
    solid = "".join(random.Random(2).choices("กขฃคฅฆงจฉชซฌญ", k=900))  # a script without blanks
    got = {r["doc_id"]: r for r in fingerprints(frame([(2, solid), (1, solid[:880] + solid[5:20])])).collect()}
    assert got[2]["near_next"] > 0.8 and len(got[2]["fingerprint"]) > 8 * 40
    assert 0.2 < fingerprints(frame([(2, solid), (1, solid[::-1])])).where("doc_id = 2").first()["near_edited"] < 0.6


def test_likeness_is_that_of_the_fingerprints(frame, words):
    docs = [(k, words(30 + k, k // 2) + " " + words(k, 50 + k)) for k in range(20)] + [(100, "one two"), (101, "one two"), (102, "!")]
    got = {r["doc_id"]: r for r in fingerprints(frame(docs)).collect()}
    cut = lambda x: {x[k : k + 8] for k in range(0, len(x), 8)}
    jaccard = lambda a, b: len(a & b) / len(a | b) if a | b else 1.0
    order = sorted(got, reverse=True)
    for k, d in enumerate(order):
        own, after = cut(got[d]["fingerprint"]), cut(got[order[(k + 1) % len(order)]]["fingerprint"])
        assert got[d]["near_next"] == pytest.approx(jaccard(own, after)) and got[d]["near_edited"] == pytest.approx(jaccard(own, cut(got[d]["edited_fingerprint"])))


def brute_syncmers(units, k, s):
    """Positions whose least inner s-mer (by the given hashes) stands at an edge."""
    inner = [units[i : i + s] for i in range(len(units) - s + 1)]
    return [i for i in range(len(units) - k + 1) if min(inner[i : i + k - s + 1]) in (inner[i], inner[i + k - s])]


def test_syncmers_equal_brute_force(spark):
    from pyspark.sql import functions as F

    from hazemedian.llm.syncmers import anchors

    units = [random.Random(k).choice("abcdefgh") * 2 for k in range(80)]
    hashes = spark.range(1).select(F.transform(F.sequence(F.lit(0), F.lit(78)), lambda i: F.xxhash64(F.get(F.lit(units), i), F.get(F.lit(units), i + 1))).alias("h")).first()["h"]
    want = [i for i in range(75) if min(hashes[i : i + 5]) in (hashes[i], hashes[i + 4])]
    got = [a["position"] for a in spark.range(1).select(anchors(F.lit(units)).alias("a")).first()["a"]]
    assert got == want == brute_syncmers([(x,) for x in hashes], 5, 1)
    assert all(b - a <= 4 for a, b in zip(got, got[1:], strict=False))  # a guaranteed anchor in every window


def test_exponent_meets_its_goals():
    tokens = {"a": 1000.0, "b": 100.0, "c": 10.0}
    alpha = bisect_alpha(tokens, target_entropy=0.9, most_epochs=1e9)
    assert entropy(weights_at(tokens, alpha)) == pytest.approx(0.9, abs=1e-9)
    alpha = bisect_alpha(tokens, target_entropy=math.log(3), most_epochs=5)
    assert max(epochs(tokens, weights_at(tokens, alpha)).values()) == pytest.approx(5, abs=1e-6)
    assert bisect_alpha({"a": 5.0}) == 1.0


def test_schedule_meets_the_budget(frame, words):
    docs = frame([(k, words(20 + k % 7, k)) for k in range(900)], source="big").union(frame([(5000 + k, words(30, k)) for k in range(120)], source="mid")).union(frame([(9000 + k, words(9, k)) for k in range(15)], source="small")).union(frame([(9100, None), (9101, "")], source=None))
    _, figures = plan(docs)
    rows = schedule(docs).collect()
    for f in figures:
        own = [r for r in rows if r["source"] == f["source"]]
        whole, rest = f["budget"] // f["tokens"], f["budget"] % f["tokens"]
        size = sum(r["n_tokens"] for r in own)
        assert f["budget"] - 27 < size <= f["budget"] or rest == 0 and size == f["budget"]
        assert all(len({r["doc_id"] for r in own if r["epoch"] == e}) == len([r for r in own if r["epoch"] == e]) for e in range(whole + 1))
        part = [r for r in own if r["epoch"] == whole]
        assert sum(r["n_tokens"] for r in part) <= rest or not part
        assert f["epochs"] <= 2 + 1e-6
    assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in docs.collect()}
    out = mixed(docs)
    assert out.columns == docs.columns and out.count() == len(rows)
    assert schedule(frame([])).count() == 0 and mixed(frame([])).count() == 0


def test_pipeline_runs_on_a_small_table(spark, tmp_path, frame, words):
    import corpus_pipeline

    item = words(40, 1)
    rows = [(k, words(60, 100 + k)) for k in range(30)] + [(100, words(60, 100)), (200, words(30, 7) + " " + item), (300, None), (301, "")]
    frame(rows).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, item)], BENCH).write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([(k, 0) for k in range(10)], "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    got = {r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == {d for d, _ in rows} - {100, 200}


def test_pipeline_keeps_null_and_repeated_ids(spark, tmp_path, frame, words):
    import corpus_pipeline

    item = words(40, 1)
    rows = [(k, words(60, 100 + k)) for k in range(20)] + [(None, words(60, 500)), (None, words(60, 501)), (None, words(60, 100)), (None, None)]
    rows += [(50, words(60, 600)), (50, words(60, 600)), (60, words(60, 601)), (60, words(60, 101)), (70, words(60, 602)), (70, words(30, 7) + " " + item)]
    frame(rows).coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, item)], BENCH).write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([(k, 0) for k in range(10)], "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    want = [*range(20), 50, 60, 70, -1, -1, -1]  # token files write a null doc_id as -1
    got = [r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).collect()]
    assert sorted(got) == sorted(want)


def test_shares_are_of_tokens_not_of_words(frame, words):
    from hazemedian.llm.tokens import count_tokens

    solid = [(k, words(300, k).replace(" ", "")) for k in range(8)]
    docs = frame(solid, source="solid").union(frame([(100 + k, words(40, k)) for k in range(8)], source="spaced"))
    n = {r["doc_id"]: r["n_tokens"] for r in count_tokens(docs).collect()}
    sized, figures = plan(docs)
    assert {r["doc_id"]: r["n_tokens"] for r in sized.collect()} == n
    tokens = {f["source"]: f["tokens"] for f in figures}
    assert tokens == {"solid": sum(n[k] for k in range(8)), "spaced": sum(n[100 + k] for k in range(8))}
    assert tokens["solid"] > 4 * tokens["spaced"]


def test_repetitive_texts_need_bounded_memory_and_time(spark, frame):
    from time import perf_counter

    from hazemedian.llm import tiling

    item = "a " * 1000
    start = perf_counter()
    got = list(tiling.Items([7], [item], 5).pairs(__import__("pyarrow").array(["a " * 20_000, "b"])))
    assert [(r, t, tiled) for r, t, _, tiled, _, _ in got] == [(0, 7, 1000)] and perf_counter() - start < 60


def test_many_benchmark_rows_of_one_id_come_in_blocks(spark, frame, words, monkeypatch):
    from hazemedian.llm import tiling

    monkeypatch.setattr(tiling, "BLOCK_BYTES", 900)
    bench = spark.createDataFrame([(1, words(30, k)) for k in range(20)], BENCH)
    got = contaminated_pairs(frame([(k, words(30, k)) for k in range(25)]), bench).collect()
    assert sorted(r["doc_id"] for r in got) == list(range(20)) and {r["item_id"] for r in got} == {1}


def brute_pairs(docs, items, match, coverage):
    import re

    cut = lambda t: re.findall(r"[0-9a-z]+", (t or "").lower())
    for d, t in docs:
        for i, u in items:
            doc, item = cut(t), cut(u)
            if item:
                tiled = sum(x[0] for x in brute_tiles(doc, item, min(match, len(item))))
                if tiled / len(item) >= coverage:
                    yield d, i, tiled


def test_contaminated_pairs_equal_brute_force(spark, frame, words):
    items = [(k, words(12 + k, 300 + k)) for k in range(6)] + [(20, "two words"), (21, None)]
    docs = []
    for k in range(40):
        rng, w = random.Random(k), items[k % 6][1].split()
        at = rng.randrange(1, len(w))
        docs.append((k, " ".join([*words(5, k).split(), *w[at:], *(words(2, 7).split() if k % 2 else []), *w[: rng.randrange(1, len(w))]]) + (" two words" if k % 5 == 0 else "")))
    got = {(r["doc_id"], r["item_id"], r["tiled_tokens"]) for r in contaminated_pairs(frame(docs), spark.createDataFrame(items, BENCH)).collect()}
    assert got == set(brute_pairs(docs, items, 5, 0.5)) and len(got) > 20


def brute_budgets(tokens, share):
    """The largest exponent of a fine grid whose weights keep the entropy, and the budgets of the smallest mixture with every document."""
    best = max((a / 4000 for a in range(4001) if entropy(weights_at(tokens, a / 4000)) >= share * math.log(len(tokens))), default=0.0)
    w = weights_at(tokens, best)
    whole = max(tokens[k] / w[k] for k in tokens)
    return {k: w[k] * whole for k in tokens}


def test_budgets_equal_a_search_over_all_exponents(frame, words):
    docs = frame([(k, words(40, k)) for k in range(60)], source="a").union(frame([(100 + k, words(40, k)) for k in range(25)], source="b"))
    _, figures = plan(docs, most_epochs=1e9)
    want = brute_budgets({f["source"]: float(f["tokens"]) for f in figures}, 0.97)
    for f in figures:
        assert f["budget"] == pytest.approx(want[f["source"]], rel=2e-3)


def test_mixing_keeps_clashing_columns_and_repeated_ids(spark, words):
    rows = [(None, words(9, 1), "a", 1, 2), (5, words(9, 2), "a", 3, 4), (5, words(9, 2), "a", 5, 6), (6, words(90, 3), "b", 7, 8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, times int, turn int")
    out = mixed(docs)
    assert out.columns == docs.columns and {tuple(r)[3:] for r in out.collect()} == {(1, 2), (3, 4), (5, 6), (7, 8)}


def test_toxicity_stage_keeps_silent_rows(spark, tmp_path, frame):
    import corpus_pipeline

    rows = [(k, f"you utter nincompoop {k}") for k in range(60)] + [(100 + k, f"calm words here {k}") for k in range(10)] + [(500, None), (501, ""), (None, "calm words here")]
    spark.createDataFrame([(d, int(d < 60)) for d, _ in rows if d is not None and d < 500], "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    got = {r["doc_id"] for r in corpus_pipeline.toxicity_stage(spark, frame(rows), str(tmp_path)).collect()}
    assert {500, 501} <= got and {100 + k for k in range(10)} <= got and not got & set(range(60))

"""Results that must not depend on the last bits of a sum, and jobs that must hold at larger sizes."""

import pytest

from hazemedian.model import NODES


@pytest.fixture
def certain(spark):
    """Packed nodes of one certain location each."""
    return lambda points: spark.createDataFrame([(i, 1.0, 1.0, [(i, p, 1.0)]) for i, p in enumerate(points)], NODES)


def test_packed_nodes_are_assigned_after_rounding(certain):
    from hazemedian.operators.costs import assign_nodes

    rows = assign_nodes(certain([[0.1234564996], [5.0]]), [[0.0], [10.0 - 1e-13]]).orderBy("node_id").collect()
    assert [(r["centre_id"], r["expected_distance"]) for r in rows] == [(0, 0.1234565), (0, 5.0)]


def _sql(folder, name):
    import glob
    import os

    import duckdb

    from hazemedian.registry import SQL

    con = duckdb.connect()
    for f in glob.glob(f"{folder}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con.sql(SQL[name]).df()


def _errors_follow_the_table(spark, tmp_path, name, table, columns, expected):
    from hazemedian.registry import QUERIES

    spark.createDataFrame(columns[0], columns[1]).write.parquet(f"{tmp_path}/{table}.parquet")
    found = sorted(tuple(r) for r in QUERIES[name](spark, str(tmp_path)).collect())
    assert found == expected
    for folder in ("/root/testdata/sf0.001",):
        ours, theirs = QUERIES[name](spark, folder).toPandas(), _sql(folder, name)
        key = list(theirs.columns)
        assert ours[key].sort_values(key).to_numpy().tolist() == theirs.sort_values(key).to_numpy().tolist()


def test_composed_errors_come_from_lineitem(spark, tmp_path):
    rows = [(1, 0.03), (1, 0.06), (2, 0.0), (3, 0.1)]
    _errors_follow_the_table(spark, tmp_path, "composed_error", "lineitem", (rows, "l_orderkey long, l_discount double"), [(1, 0.0302), (2, 0.0), (3, 0.033333)])


def test_level_errors_come_from_events(spark, tmp_path):
    rows = [(1,)] * 7 + [(2,)] * 16 + [(3,)] * 39
    eps = [round(1.2 ** (1 / k) - 1, 9) for k in (1, 2, 3)]
    _errors_follow_the_table(spark, tmp_path, "level_epsilon", "events", (rows, "user_id long"), [(1, 1, eps[0]), (2, 2, eps[1]), (3, 3, eps[2])])


def test_full_data_solver_scans_what_no_task_can_hold(spark, monkeypatch):
    """Scans give the same centres whatever the partitions, at the cost of the one-task solver, and the measures use them."""
    import numpy as np

    from hazemedian.plans import baselines, experiment
    from hazemedian.plans.full_data import solve_full
    from hazemedian.sources.workloads import workload

    nodes, d = workload(spark, "/root/testdata/sf0.001", "orders_absent")
    one, two = (solve_full(nodes.repartition(n), [(5, 1), (3, 2)]) for n in (1, 4))
    assert all(np.allclose(one[r][0], two[r][0]) for r in one)
    assert one[5, 1][1] <= 1.1 * baselines.full_solver_local(nodes, 5, 1)[1]
    monkeypatch.setattr(experiment, "TASK_BYTES", 0)
    monkeypatch.setattr(baselines, "full_solver_local", None)
    m = experiment.run(spark, nodes, d, "orders", ["full_solver"], [5], [1]).first()
    assert m["cost_full"] == pytest.approx(one[5, 1][1]) and m["gap"] == 0


def test_repetitions_never_shuffle_nodes(spark, monkeypatch):
    """Only summaries meet: a group holds a few budgets, however many nodes there are, and every repetition reads all of them."""
    from dataclasses import replace

    from hazemedian.model import PRACTICAL
    from hazemedian.plans import experiment

    rows = [(i, 1.0, 1.0, [(i, [float(i % 7), float(i % 11)], 1.0)]) for i in range(9000)]
    nodes, grouped = spark.createDataFrame(rows, NODES).repartition(4), []
    kind, old = type(nodes), type(nodes).groupBy
    monkeypatch.setattr(kind, "groupBy", lambda self, *c: grouped.append(self.count()) or old(self, *c))
    found = experiment.repeated(nodes, 2, 12, replace(PRACTICAL, per_k=10, capacity=64)).collect()
    assert sorted(r["seed"] for r in found) == list(range(1, 13)) and max(grouped) < 12 * len(rows)
    assert all(r["summary_rows"] <= 16 * 64 + 20 and r["gap"] < 0.5 and r["cost_full"] > 0 for r in found)


def test_links_are_those_of_all_pairs(spark, monkeypatch):
    """Blocks dealt over tasks, copies, repeated and missing ids, missing blocks: the sums of the pairs, which are written out here."""
    import numpy as np
    from pyspark.sql import functions as F

    from hazemedian.operators import nodes

    rng = np.random.default_rng(3)
    rows = [(i // 2 if i % 9 == 0 else i, rng.integers(0, 4, 3).astype(float).tolist(), "a" if i < 90 else "b") for i in range(140)]
    rows += [(None, [1.0, 1.0, 1.0], "a"), (None, [0.0, 9.0, 0.0], "b"), (500, [0.0, 0.0, 0.0], None), (501, [7.0, 7.0, 7.0], "c")]
    points = spark.createDataFrame(rows, "node_id long, coords array<double>, part string")
    left = points.select("node_id", F.col("coords").alias("own"), "part")
    score = F.lit(1.0) - F.lit(0.3) * sum(F.abs(F.get("own", F.lit(k)) - F.get("coords", F.lit(k))) for k in range(3))
    packed = nodes.pack(nodes.match_nodes(left, points.withColumnRenamed("node_id", "loc_id"), "part", score))
    expected = {r["node_id"]: (r["n"], r["mass"]) for r in packed.select("node_id", "mass", F.size("support").alias("n")).collect()}
    assert None in expected and 500 not in expected
    for size in (nodes.TASK_POINTS, 7):
        monkeypatch.setattr(nodes, "TASK_POINTS", size)
        found = nodes.match_links(points, "part", 0.3).collect()
        assert {r["node_id"]: r["n"] for r in found} == {k: n for k, (n, _) in expected.items()} and len(found) == len(expected)
        if size == 7:
            assert {r["node_id"]: r["score"] for r in found} == pytest.approx(scores)
        scores = {r["node_id"]: r["score"] for r in found}
    least = {}
    for i, x, part in rows:
        if i is not None and part is not None:
            least[part, *x] = min(i, least.get((part, *x), i))
    own = {}
    for i, x, part in rows:
        own.setdefault(i, []).append(least.get((part, *x)))
    assert all(r["class_id"] == min(own[r["node_id"]]) for r in found if r["node_id"] is not None)


def test_match_totals_over_several_sides():
    import numpy as np

    from hazemedian import kernels

    rng = np.random.default_rng(4)
    x, y = rng.random((2 * kernels.PAIR_SIDE + 9, 4)), rng.random((kernels.PAIR_SIDE + 1, 4))
    c, d = rng.integers(1, 5, len(x)), rng.integers(1, 5, len(y))
    for y, d in ((x, c), (y, d)):
        score = np.maximum(0.0, 1 - 1.5 * np.abs(x[:, None] - y[None]).sum(2))
        of_x, of_y = kernels.match_totals(x, c, y, d, 1.5)
        assert np.allclose(of_x, np.stack([score @ d, (score > 0) @ d], 1)) and np.allclose(of_y, np.stack([c @ score, c @ (score > 0)], 1))


def test_matches_of_a_large_block_are_not_shuffled(spark, tmp_path):
    """1,200 different documents of one length class, nearly all of them linked: a task writes its documents, not their 1.4 million pairs."""
    from hazemedian.registry import QUERIES

    words = [f"w{i}" for i in range(40)]
    rows = [(i, " ".join([*words, *(words[:8] * 5)[i % 29 : i % 29 + 9], f"x{i}"]), "en", "a", 300) for i in range(1200)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")

    def written():
        spark._jsc.sc().listenerBus().waitUntilEmpty()
        each = spark._jsc.sc().statusStore().executorList(True)
        return sum(each.apply(k).totalShuffleWrite() for k in range(each.size()))

    before = written()
    found = QUERIES["match_nodes"](spark, str(tmp_path)).collect()
    assert written() - before < 1000 * len(rows)
    assert len(found) == len(rows) and sum(r["n"] for r in found) > 1e6


def _shuffled(spark):
    spark._jsc.sc().listenerBus().waitUntilEmpty()
    each = spark._jsc.sc().statusStore().executorList(True)
    return sum(each.apply(k).totalShuffleWrite() for k in range(each.size()))


def test_stored_blocks_are_small_and_not_shuffled(spark, tmp_path):
    """Messages and row groups hold a few blocks of BLOCK_PAIRS locations, which give all numbers back; a larger node is a block."""
    import glob

    import numpy as np
    import pyarrow.parquet as pq

    from hazemedian.plans import full_data

    rng = np.random.default_rng(5)
    point = lambda: [*rng.integers(0, 2, 30).astype(float).tolist(), 0.5, -1.0, float(rng.random())]
    rows = [(i, 1.0, 1.0, [(10 * i + j, point(), 0.1) for j in range(10)]) for i in range(3000)]
    rows.append((9999, 2.0, 1.0, [(10**6 + j, point(), 1 / 5000) for j in range(5000)]))
    nodes, before = spark.createDataFrame(rows, NODES), _shuffled(spark)
    blocks = full_data.stored_blocks(nodes)
    assert _shuffled(spark) == before
    found, sizes = {}, []
    for row in blocks.collect():
        x = full_data._wide(row.asDict(), len(row["prob"]) // 8)
        found |= dict(zip(np.frombuffer(row["loc_id"], "<i8").tolist(), x.T.tolist(), strict=True))
        sizes.append((x.shape[1], len(row["coords"])))
    assert found == {i: x for _, _, _, support in rows for i, x, _ in support}
    assert all(n <= full_data.BLOCK_PAIRS or n == 5000 for n, _ in sizes) and sum(b for _, b in sizes) < 35000 * 33 * 8 / 4
    groups = [pq.ParquetFile(f).metadata for f in glob.glob(f"{blocks.inputFiles()[0].rsplit('/', 1)[0].removeprefix('file:').replace('//', '')}/*.parquet")]
    assert max(m.row_group(i).total_byte_size for m in groups for i in range(m.num_row_groups)) < 4 * full_data.GROUP_BYTES


def test_small_steps_end_and_ended_centres_are_not_scanned(spark, monkeypatch):
    """Centres whose steps become a tenth each time end at SETTLED, where the further scans wouldn't move them."""
    import numpy as np

    from hazemedian.plans import full_data
    from hazemedian.sources.workloads import workload

    nodes, _ = workload(spark, "/root/testdata/sf0.001", "census")
    asked, old = [], full_data.scanned
    monkeypatch.setattr(full_data, "scanned", lambda blocks, questions: asked.append(questions) or old(blocks, questions))
    runs = [(3, 1), (4, 2)]
    found, few = full_data.solve_full(nodes, runs), len(asked)
    assert any(len(q[1][1]) < len(q[1][0]) for x in asked for q in x if q[0] == "step")
    monkeypatch.setattr(full_data, "SETTLED", 0)
    whole = full_data.solve_full(nodes, runs)
    assert few < 0.8 * (len(asked) - few)
    for r in runs:
        assert np.allclose(found[r][0], whole[r][0], atol=1e-7) and found[r][1] == pytest.approx(whole[r][1], rel=1e-9) and found[r][2] == whole[r][2]


def test_coordinates_of_chunks_are_made_behind_the_shuffles(spark):
    from pyspark.sql import functions as F

    from hazemedian.operators import nodes

    points = spark.range(20003).select((F.col("id") * 7 % 20011).alias("id"), F.rand(3).alias("u"))
    coords = F.array(*(F.col("u") * F.lit(1 / 7 + k) for k in range(150)))
    before = _shuffled(spark)
    found = nodes.chunk_nodes(points, ["id"], coords).select("node_id", "weight", "mass", "support").collect()
    assert _shuffled(spark) - before < 20003 * 150
    assert sorted(found) == sorted(nodes.pack(nodes.chunk_realisations(points, ["id"], coords)).collect())


def test_pairs_of_the_product_are_made_in_several_tasks(spark):
    from pyspark.sql import functions as F

    from hazemedian.sources.workloads import big_cross_points

    part, supplier = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet").select(F.pmod(F.xxhash64(k), F.lit(10)).alias(t)) for t, k in (("part", "p_partkey"), ("supplier", "s_suppkey")))
    whole = part.crossJoin(supplier).where("part = supplier").count()
    rows, _ = big_cross_points(spark, "/root/testdata/sf0.01")
    each = [r["count"] for r in rows.groupBy(F.spark_partition_id()).count().collect()]
    assert sum(each) == whole and len(each) >= 4 and max(each) < 0.5 * sum(each)


def test_summary_runs_share_the_passes_over_a_large_input(spark, monkeypatch):
    """One pass for all ladders and one for all costs, with the results of single runs."""
    from dataclasses import replace

    from hazemedian.model import PRACTICAL
    from hazemedian.plans import experiment
    from hazemedian.sources.workloads import workload

    nodes, d = workload(spark, "/root/testdata/sf0.001", "orders_absent")
    small = replace(PRACTICAL, per_k=10, capacity=128)
    args = spark, nodes, d, "orders", ["summary"], [3, 5], [1, 2], small
    one = experiment.run(*args).drop("seconds").collect()
    monkeypatch.setattr(experiment, "TASK_BYTES", 0)
    monkeypatch.setattr(experiment, "run_method", None)
    kind, passes, old = type(nodes), [], type(nodes).mapInArrow
    monkeypatch.setattr(kind, "mapInArrow", lambda self, *a, **b: passes.append(1) or old(self, *a, **b))
    two = experiment.run(*args).drop("seconds").collect()
    assert len(passes) == 2 and len(one) == len(two) == 4
    for x, y in zip(one, two, strict=True):
        assert x[:4] == y[:4] and x["summary_rows"] == y["summary_rows"] and y["cost_full"] == pytest.approx(x["cost_full"], rel=0.02) and y["cost_summary"] == pytest.approx(x["cost_summary"], rel=0.05)

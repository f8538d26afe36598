"""Planner, estimator, experiments and streams on small planted inputs."""

from dataclasses import replace

import pytest

from hazemedian.model import PRACTICAL
from hazemedian.plans import experiment, planner
from hazemedian.plans.summarise import UncertainKMedian, flat_reduce, summarise
from hazemedian.sources.tables import PlantedNodes, kept
from hazemedian.sources.workloads import WORKLOADS, workload

SF = "/root/testdata/sf0.001"
SMALL = replace(PRACTICAL, per_k=40, capacity=512)


@pytest.fixture(scope="module")
def planted(spark):
    spark.dataSource.register(PlantedNodes)
    return kept(spark.read.format("planted_nodes").option("n", 1200).load().drop("planted"))


def test_planner_and_estimator(planted):
    chosen = planner.plan(planted, 5, SMALL)
    assert chosen["route"] == "summary" and chosen["d"] == 2 and chosen["kernel"] == "wide" and chosen["profile"].capacity >= 400
    assert planner.plan(planted, 30, SMALL)["route"] == "direct"
    model = UncertainKMedian(5, SMALL, restarts=3).fit(planted)
    assert model.result.gap < 0.2
    assert model.transform(planted).groupBy("centre_id").count().count() == 5


def test_summary_keeps_weight_whatever_the_partitions(planted):
    for n in (1, 5):
        found = summarise(planted.repartition(n), 5, SMALL)
        assert found.agg({"weight": "sum"}).first()[0] == pytest.approx(1200)
        assert found.count() < 500
    assert flat_reduce(planted, 5, SMALL).agg({"weight": "sum"}).first()[0] == pytest.approx(1200)


def test_measures(spark, planted):
    m = kept(experiment.run(spark, planted, 2, "planted", ["summary", "full_solver"], [4, 5, 300], [1, 2], SMALL, restarts=3))
    assert {r["note"] for r in m.where("k = 300 and method = 'summary'").collect()} == {"skipped: the summary would be too large"}
    assert all(r["ratio"] < 1.1 for r in experiment.quality_ratio(m).where("method = 'summary' and k = 5").collect())
    assert experiment.run_statistics(m).where("runs = 2").count() >= 4
    for f in (experiment.gap_quality_link, experiment.time_linearity, experiment.time_ratio, experiment.throughput, experiment.per_k_table):
        assert f(m).count() > 0
    assert experiment.ladder_statistics(8 * 13 + 2, 8)["occupancy"] == "1011"


def test_far_planted_groups_favour_cells_over_uniform_samples(spark):
    """The stress workload: the median summary gap is not larger than a uniform sample's of the same budget."""
    nodes, d = workload(spark, SF, "customers")
    m = experiment.run(spark, nodes, d, "customers", ["summary", "uniform_sample"], [10], [1, 2, 3, 4, 5], replace(PRACTICAL, per_k=4, capacity=100), restarts=2)
    gap = {r["method"]: r["mean"] for r in experiment.run_statistics(m, "gap").collect()}
    assert gap["summary"] < 1


@pytest.mark.parametrize("name", ["cover", "census", "cross", "descriptors", "orders_absent", "suppliers", "matches"])
def test_workload_dimensions(spark, name):
    d, build = WORKLOADS[name]
    nodes = build(spark, SF)
    row = nodes.selectExpr("size(support[0].coords) AS d", "mass").first()
    assert row["d"] == d and 0 < row["mass"] <= 1 + 1e-9


def test_stream_of_panes_and_scoring(spark, tmp_path):
    from hazemedian.sources.tables import table
    from hazemedian.streaming import ladder_stream as s

    events = table(spark, SF, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    s.write_slices(events, str(tmp_path / "slices"), 400)
    rows = s.events_stream(spark, f"{tmp_path}/slices/*")
    found = s.score_stream(s.user_panes(rows), [[0.2, 0.2, 0.2], [0.8, 0.8, 0.8]])
    q = found.writeStream.format("memory").queryName("scored").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("scored").count() > 100
    panes = s.user_panes(events.withColumn("ts", events.ts.cast("timestamp")).withColumn("coords", s.event_coords()))
    out = s.windowed_summaries(panes, 2, SMALL)
    assert out.select("pane").distinct().count() == panes.select("pane").distinct().count()

import pytest
from gridknn.functions.vote import majority
from gridknn.operators import points, quality
from gridknn.operators.grid import GridSpec
from gridknn.operators.local import NN
from gridknn.plans import cost, pipeline, workloads
from gridknn.plans.profiles import PROFILES
from gridknn.plans.registry import ORACLE, QUERIES
from gridknn.sources import datagen, io
from gridknn.streaming import classify as streaming
from pyspark.sql import functions as F

from .conftest import SF

#: Cells of the smallest tables hold too few points for rates and balances to mean anything.
LARGER = "/root/testdata/sf0.01"


def votes(spark, classes, **options):
    rows = [(0, [(float(i), i, c) for i, c in enumerate(classes)])]
    frame = spark.createDataFrame(rows, f"pid long, nn {NN}")
    return frame.select(majority(F.col("nn"), **options).alias("v")).first().v


def test_votes(spark):
    assert votes(spark, ["B", "A", "A", "B"]).cls_pred == "B"
    assert votes(spark, ["B", "A", "A", "B"], tie="class").cls_pred == "A"
    assert votes(spark, ["C", "B", "A", "D"]).best_rank == 1
    assert votes(spark, ["B", "A", "A"]).votes == 2
    assert votes(spark, ["B", "A", "A"], weighted=True).cls_pred == "B"
    assert votes(spark, []) is None


def test_rates_of_a_hand_made_matrix(spark):
    cells = spark.createDataFrame([("A", "A", 8), ("A", "B", 2), ("B", "B", 5), ("B", "C", 5), ("C", "C", 20)], "truth string, pred string, n long")
    got = {r.cls: r for r in quality.rates(cells).collect()}
    assert got["A"].tp == 0.8 and got["A"].fp == 0 and got["B"].tp == 0.5
    assert got["B"].fp == pytest.approx(2 / 30) and got["C"].fp == pytest.approx(5 / 20)
    assert all(r.tp + r.fn == pytest.approx(1) and r.fp + r.tn == pytest.approx(1) for r in got.values())
    assert quality.macro(quality.rates(cells)).first().tp == pytest.approx((0.8 + 0.5 + 1) / 3)
    assert quality.accuracy(cells).first().accuracy == pytest.approx(33 / 40)


def test_published_rates_average_as_published(spark):
    rows = [("A", 99.97, 0.03, 0.13, 99.87), ("B", 99.91, 0.09, 0.06, 99.94), ("C", 94.14, 5.86, 0.06, 99.94)]
    out = quality.macro(spark.createDataFrame(rows, "cls string, tp double, fn double, fp double, tn double")).first()
    assert (round(out.tp), round(out.fn), round(out.fp, 2), round(out.tn, 2)) == (98, 2, 0.08, 99.92)


def test_classes_from_coordinates_are_recovered(spark):
    out = {r.cls: r for r in workloads.quality_rates(spark, LARGER).collect()}
    assert set(out) == {"A", "B", "C", "average"}
    assert out["A"].tp > 0.85 and out["average"].fp < 0.1


def test_measures_follow_k_and_merging(spark):
    small, large = ({r.measure: r.value for r in workloads.measured(spark, SF, "skew2", k, 3).collect()} for k in (5, 20))
    assert small["pairs_primitive"] == large["pairs_primitive"]
    assert small["overlaps"] <= large["overlaps"] and small["updates"] <= large["updates"]
    merged = [r.merged_cells for r in workloads.merge_statistics(spark, SF, "unif2", (5, 10, 20)).collect()]
    assert merged == sorted(merged)
    failed = workloads.measured(spark, SF, "skew2", 5, 3, "merge", limit=10).collect()
    assert [r.measure for r in failed] == ["failed"]
    uneven = {r.profile: r.unevenness for r in workloads.distributions(spark, LARGER).collect()}
    assert uneven["skew2"] > uneven["unif2"]


def test_short_queries_are_those_with_short_lists(spark):
    train, query = PROFILES["skew2"].split(spark, SF)
    run = pipeline.search(query, train, 5, GridSpec.pow2(2, 3))
    got = {r.measure: r.value for r in cost.measures(run).collect()}
    assert got["short_queries"] == sum(len(r.nn) < 5 for r in run.own.collect()) > 0
    assert got["done_queries"] + got["short_queries"] <= query.count()


def test_training_set_is_prepared_once(spark, monkeypatch):
    train, query = PROFILES["skew2"].split(spark, SF)
    ready = pipeline.prepare(train, GridSpec.pow2(2, 3))
    want = sorted(map(tuple, pipeline.all_knn(query, train, 5, GridSpec.pow2(2, 3)).collect()))
    monkeypatch.setattr(pipeline, "cell_counts", None)
    monkeypatch.setattr(pipeline, "train_blocks", None)
    assert sorted(map(tuple, pipeline.all_knn(query, ready, 5).collect())) == want


def test_physical_forms_agree_on_any_minkowski(spark):
    train, query = PROFILES["unif2"].split(spark, SF)
    rows = [{(r.pid, r["rank"], r.tid) for r in pipeline.all_knn(query, train, 5, GridSpec.pow2(2, 2), metric="minkowski1.23456789", physical=p).collect()} for p in ("arrow", "blocked", "pairs")]
    assert rows[0] == rows[1] == rows[2]


def test_workload_tables(spark):
    pairs = workloads.own_cell_pairs(spark, SF, "unif2", (2, 4)).collect()
    by = {(r.n, r.method): r.pairs for r in pairs}
    assert by[2, "grow"] > by[4, "grow"] and by[4, "merge"] >= by[4, "grow"]
    times = workloads.total_times(spark, SF, "unif2")
    assert {r.method for r in times.collect()} == {"grow", "merge", "brute"}
    assert workloads.speedup(times).filter("speedup = 1").count() == 3
    phases = {r.phase for r in workloads.phase_times(spark, SF, "unif2", (5,)).collect()}
    assert phases == {"distribution", "merging", "primitive", "overlap", "update", "integrate", "classification"}


def test_no_quadratic_join_in_the_plan(spark):
    train, query = PROFILES["unif2"].split(spark, SF)
    plan = pipeline.search(query, train, 5, GridSpec.pow2(2, 3)).final._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_bad_rows_are_set_apart(spark):
    nan, inf = float("nan"), float("inf")
    frame = spark.createDataFrame([(1, [0.1, 0.2]), (2, [nan, 0.1]), (3, [inf, 0.1]), (4, [0.1]), (5, None), (None, [0.1, 0.2])], "pid long, coords array<double>")
    good, bad = points.validate(points.from_arrays(frame, 2, cls=None), 2)
    assert [r.pid for r in good.collect()] == [1] and bad.count() == 5


def test_files(spark, tmp_path):
    pts = datagen.power_law(spark, 50, 2)
    assert datagen.uniform(spark, 10, 3).columns == ["pid", "x0", "x1", "x2", "cls"]
    text = pts.select(F.concat_ws(",", "pid", "x0", "x1", "cls").alias("value"))
    io.write(text, str(tmp_path / "t"), "text")
    assert sorted(r.pid for r in io.read_text(spark, str(tmp_path / "t"), 2).collect()) == list(range(50))
    io.write(pts, str(tmp_path / "j"), "json")
    assert io.read_json(spark, str(tmp_path / "j"), points.PointSpec("pid", ("x0", "x1"), "cls")).count() == 50
    io.write_clustered(points.as_train(pts, 2), GridSpec.pow2(2, 2), str(tmp_path / "c"), 2)
    assert spark.read.parquet(str(tmp_path / "c")).count() == 50


def test_stream_answers_like_a_batch(spark, tmp_path):
    train, query = PROFILES["unif2"].split(spark, SF)
    grid = GridSpec.pow2(2, 3)
    query = query.filter("pid < 200").withColumn("ts", F.timestamp_seconds(F.col("pid") * 60))
    query.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(query.schema).parquet(str(tmp_path / "in"))
    streaming.classify_stream(stream, train, 5, grid, lambda df, n: df.write.mode("append").parquet(str(tmp_path / "out")), str(tmp_path / "cp")).awaitTermination()
    want = {(r.pid, r.cls_pred) for r in pipeline.classify(query.drop("ts"), train, 5, grid).collect()}
    assert {(r.pid, r.cls_pred) for r in spark.read.parquet(str(tmp_path / "out")).collect()} == want


def test_late_rows_are_dropped_and_windows_counted(spark, tmp_path):
    def put(name, rows):
        spark.createDataFrame(rows, "id long, at long, cls string").select("id", F.timestamp_seconds("at").alias("ts"), "cls").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))

    put("a", [(1, 0, "A"), (2, 100, "A"), (3, 90_000, "B")])
    stream = spark.readStream.schema("id long, ts timestamp, cls string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    start = lambda: streaming.class_counts(stream, "ts", "cls").writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination()
    start()
    put("b", [(4, 10, "A"), (5, 300_000, "B")])  # the first comes a day too late
    start()
    got = {(r["window"].start.day, r.cls): r.n for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got[(1, "A")] == 2


def test_registry(spark):
    assert len(QUERIES) > 40 and set(ORACLE) <= set(QUERIES)
    assert QUERIES["knn_one_point"](spark, SF).count() == 10


def test_record_bytes_grow():
    assert cost.record_bytes(20, 3) > cost.record_bytes(5, 3) > cost.record_bytes(5, 1)


def test_recall_counts_copies_of_queries(spark):
    make = lambda rows: spark.createDataFrame([(i, [(0.0, t, "A") for t in tids]) for i, tids in rows], f"pid long, nn {NN}")
    copies = spark.createDataFrame([(0, 3), (1, 1)], "pid long, copies long")
    out = quality.recall(make([(0, [1, 2]), (1, [3, 9])]), make([(0, [1, 2]), (1, [3, 4])]), copies).first()
    assert (out.queries, out.exact_lists, out.recall) == (4, 3, 3.5 / 4)
    none = make([(0, [1])]).filter("false")
    assert quality.recall(none, none).first().queries == 0


def test_measures_count_copies_of_queries_and_a_cell_once_in_many_chunks(spark, monkeypatch):
    """Cells whose points lie in several chunks are one update each; places stand for all their queries."""
    from gridknn.operators import local

    train, query = PROFILES["skew2"].split(spark, SF)
    query = query.unionByName(query.withColumn("pid", F.col("pid") + 10_000)).unionByName(query.withColumn("pid", F.col("pid") + 20_000))
    grid = GridSpec.pow2(2, 2)
    want = {r.measure: r.value for r in cost.measures(pipeline.search(query, train, 5, grid)).collect()}
    assert want["updates"] == query.count() + want["overlaps"]
    monkeypatch.setattr(local, "CHUNK", 4)
    assert {r.measure: r.value for r in cost.measures(pipeline.search(query, train, 5, grid)).collect()} == want
    seen = pipeline.shared_places(query, 2)
    assert 0 < seen.count() <= query.count() / 3
    assert {r.measure: r.value for r in cost.measures(pipeline.search(seen.drop("copies"), train, 5, grid), seen).collect()} == want

"""The measures show the reported behaviour: what each variant trades, and how costs move with load and size."""

from pyspark.sql import functions as F

from splitcount import api, measures

from .conftest import SF


def test_changes_die_out_with_the_load(spark):
    rows = {(r["variant"], r["p"], r["load"]): r for r in measures.load_factor(spark, [6, 8], 8, reps=3).collect()}
    for p in (6, 8):
        calls = [rows["opt", p, 1 << k]["compress_calls"] / (2**p << k) for k in range(8)]
        assert calls[-1] < calls[0] / 4  # fewer base searches per item
        assert rows["lazy", p, 128]["compress_calls"] < rows["opt", p, 128]["compress_calls"] / 5


def test_merges(spark):
    rows = {(r["variant"], r["p"]): r for r in measures.merge_time(spark, [10, 18], reps=3).collect()}
    assert rows["opt", 18]["seconds"] < 1 / 3
    assert rows["min", 18]["sparse"] > 1.5 * rows["opt", 18]["sparse"]  # its sparse part is overused
    assert rows["opt", 18]["seconds"] > rows["opt", 10]["seconds"]


def test_tradeoff(spark):
    rows = {(r["variant"], r["p"]): r for r in measures.tradeoff(spark, [10], 40_000).collect()}
    assert rows["opt", 10]["bits"] <= rows["lazy", 10]["bits"] <= rows["min", 10]["bits"] < rows["reg6", 10]["bits"]
    assert rows["zstd", 10]["per_item"] > rows["lazy", 10]["per_item"]
    assert ("zstd", 10) not in {(r["variant"], r["p"]) for r in measures.front(measures.tradeoff(spark, [10], 20_000)).collect()} or rows["zstd", 10]["bits"] < rows["opt", 10]["bits"]


def test_build_times_come_with_every_variant(spark):
    got = measures.update_time(spark, 20_000, 8, reps=1).collect()
    assert {r["variant"] for r in got} >= {"reg6", "split_opt", "pairs", "builtin_improved"} and all(r["seconds"] > 0 for r in got)
    assert measures.hash_only(spark.read.parquet(f"{SF}/documents.parquet"), "text", reps=1) > 0


def test_public_surface(spark):
    line = spark.read.parquet(f"{SF}/lineitem.parquet")
    a = api.distinct_registers(line.where("l_linenumber <= 3"), [], F.col("l_orderkey").cast("string"))
    b = api.distinct_registers(line.where("l_linenumber >= 3"), [], F.col("l_orderkey").cast("string"))
    got = api.overlap(a, b).first()
    assert 0 < got["inter_est"] < got["union_est"] and 0 < got["jaccard"] < 1
    est = {r["l_returnflag"]: r["est"] for r in api.approx_distinct(line, ["l_returnflag"], F.col("l_orderkey").cast("string")).collect()}
    exact = {r[0]: r[1] for r in line.groupBy("l_returnflag").agg(F.count_distinct("l_orderkey")).collect()}
    assert all(abs(est[k] / n - 1) < 0.1 for k, n in exact.items())
    rows = api.compare_variants(line, "l_orderkey", [6, 8]).collect()
    assert len(rows) == 4 and all(r["bits"] > 0 for r in rows)
    assert "HashAggregate" in str(measures.plan_stats(a))

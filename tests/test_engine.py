"""Accuracy gates, theorem gates, plan shapes, physical forms, stores and streams."""

import pytest
from pyspark.sql import functions as F

from splitcount import accuracy, workloads
from splitcount.functions import theory as T
from splitcount.functions.hashing import pairs
from splitcount.operators import aggregate as A
from splitcount.operators import baselines as B
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators import split as S
from splitcount.plans.choose import choose_form, executed_plan, shuffle_bytes
from splitcount.schema import VARIANT_IDS
from splitcount.sources import pairs_source
from splitcount.sources.store import SketchStore
from splitcount.streaming import panes

from .conftest import SF


def items(spark, n, groups=1):
    return spark.range(n).select(F.concat(F.lit("g"), F.col("id") % groups).alias("g"), F.col("id").cast("string").alias("v"))


# ---- accuracy and theory


def test_error_follows_the_rule(spark):
    for p, n in ((6, 2000), (8, 4000)):
        got = accuracy.spread(spark, n, p, 30).first()
        assert 0.6 * T.rse(p) < got["rmse"] < 1.5 * T.rse(p)
        assert abs(got["mean_err"]) < 4 * T.rse(p) / 30**0.5


def test_closed_sizes_match_the_published_ones(spark):
    rows = {r["p"]: r for r in workloads.closed_sizes(spark).collect()}
    assert 0.370 < rows[18]["reduction"] < 0.380
    assert sum(r["reduction"] for r in rows.values()) / len(rows) > 0.41
    assert abs(rows[10]["entropy"] - 2.832) < 1e-3


def test_sampled_sizes_match_closed_ones(spark):
    rows = {(r["p"], r["variant"]): r["per_register"] for r in workloads.sizes_at(spark, 2.0**30, (10, 12)).collect()}
    for p in (10, 12):
        assert rows[p, "split_opt"] == pytest.approx(T.expected_bits(2.0**30, p) / 2**p, rel=0.05)
        assert rows[p, "split_opt"] <= rows[p, "split_min"]
    assert rows[12, "split_min"] > rows[12, "split_opt"] * 1.05


def test_all_registers_fit_gate(spark):
    bits, least = T.bits_all(6, 0.5)
    delta = T.delta_all(6, 0.5)
    assert (bits, least) == (4, 16384.0)
    regs = R.from_pairs(workloads.raw_pairs(spark, 20_000, 6, rep=4).select("j", "r"), [])
    n = spark.createDataFrame([(20_000,)], "n long")
    assert T.outliers(S.histogram(regs, [], 6), n, [], 6, delta).first()["outliers"] == 0


def test_split_gate(spark):
    b = T.bits_split(8)
    n = int(b["least_n"]) + 1
    regs = R.from_pairs(workloads.raw_pairs(spark, n, 8, rep=2).select("j", "r"), [])
    got = T.outliers(S.histogram(regs, [], 8), spark.createDataFrame([(n,)], "n long"), [], 8, b["delta"]).first()
    assert got["outliers"] <= b["outliers"]


def test_tails_and_scalars():
    low, a, b = T.tail_bounds(3.0)
    assert low < a == b == 0.125
    assert T.chernoff(1.0, 30) == pytest.approx(4.54e-5, rel=0.01)
    assert T.succinct_bits(0, 100) == 0 and T.succinct_bits(25, 100) == 50
    assert not T.amortised(2.0**30, 15)["constant"] and T.amortised(2.0**42, 12)["constant"]
    assert sum(T.pmf(1e6, 10)) == pytest.approx(1.0)
    assert T.size_formula(12, 2.0**30)["split"] < T.size_formula(12, 2.0**30)["plain"] * 2


def test_registers_are_negatively_dependent(spark):
    got = T.covariance(workloads.outlier_flags(spark, 400, 4, 1.5, 150)).first()
    assert got["joint"] <= got["product"] + 3 * 0.25 / 150**0.5


def test_law_matches_counts(spark):
    regs = R.from_pairs(workloads.raw_pairs(spark, 1 << 16, 10).select("j", "r"), [])
    h = {r["r"]: r["c"] / 1024 for r in S.histogram(regs, [], 10).collect()}
    assert sum(abs(x - h.get(k, 0)) for k, x in enumerate(T.pmf(1 << 16, 10))) / 2 < 0.06


def test_baselines_are_near(spark):
    df = items(spark, 30_000)
    rows = pairs(df, ["g"], "v", 10)
    h = S.histogram(R.from_pairs(rows, ["g"]), ["g"], 10)
    ests = {
        "loglog": B.loglog(h, ["g"], 10),
        "super": B.super_loglog(h, ["g"], 10),
        "matrix": B.bitmatrix(rows, ["g"], 10),
        "coded": B.bitmatrix_coded(rows, ["g"], 10),
        "kmin": B.kmin(df, ["g"], "v", 1024),
        "mle": E.likelihood(h, ["g"], 10),
        "improved": B.builtin_improved(df, ["g"], "v", 0.03),
        "library": B.builtin_sketch(df, ["g"], "v"),
        "theta": B.builtin_theta(df, ["g"], "v"),
    }
    for name, df2 in ests.items():
        assert df2.first()["est"] == pytest.approx(30_000, rel=0.16), name
    cut = B.tailcut(h, ["g"], 10).first()
    assert cut["bits"] == 3 * 1024 and cut["est"] <= E.from_hist(h, ["g"], 10).first()["est"] + 1e-6
    order = pairs(spark.range(20_000), ["id"], F.col("id").cast("string"), 10)
    assert B.martingale(order, 10, "id").first()["est"] == pytest.approx(20_000, rel=0.12)


# ---- plans


def test_build_plan_has_one_partial_and_one_final_maximum(spark):
    df = spark.read.parquet(f"{SF}/lineitem.parquet")
    plan = executed_plan(R.build(df.where("l_quantity > 25"), ["l_returnflag"], F.col("l_orderkey").cast("string"), 10))
    assert plan.count("HashAggregate(") == 2 and plan.count("Exchange hashpartitioning") == 1
    assert "partial_max" in plan and "Python" not in plan
    assert "GreaterThan(l_quantity,25.0)" in plan.split("PushedFilters: ")[1].split("ReadSchema")[0]
    assert "ReadSchema: struct<l_orderkey:bigint,l_quantity:double,l_returnflag:string>" in plan
    assert plan.count("md5(") == 1  # the hash is computed once per row


def test_base_search_reads_histograms_only(spark):
    df = spark.read.parquet(f"{SF}/lineitem.parquet")
    regs = R.build(df, ["l_returnflag"], F.col("l_orderkey").cast("string"), 10)
    plan = executed_plan(S.best_base(S.histogram(regs, ["l_returnflag"], 10), ["l_returnflag"], 10))
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_form_choice():
    assert choose_form(12, 1, 1, 0) == "relational"
    assert choose_form(12, 1000, 1, 10**7) == "partial" and choose_form(12, 1000, 10**6, 1000) == "relational"
    sent = shuffle_bytes(10, 10, 1, 10**6)
    assert sent["partial"] < sent["relational"]


# ---- forms and stores


def test_two_forms_give_the_same_bytes(spark):
    df = items(spark, 5000, 3).repartition(5)
    for p in (4, 9):
        a = {r["g"]: bytes(r["sketch"]) for r in A.distinct_sketch(df, ["g"], "v", p, form="relational").collect()}
        b = {r["g"]: bytes(r["sketch"]) for r in A.distinct_sketch(df, ["g"], "v", p, form="partial").collect()}
        assert a == b and len(a) == 3


def test_grouped_rows_reach_memory_in_bounded_tables(spark):
    df = items(spark, 300, 60)
    few = A.merge_sketches(A.partial_sketches(df, ["g"], "v", 4, max_groups=7), ["g"], fan_in=2)
    want = A.distinct_sketch(df, ["g"], "v", 4, form="relational")
    assert {r["g"]: bytes(r["sketch"]) for r in few.collect()} == {r["g"]: bytes(r["sketch"]) for r in want.collect()}


def test_no_merge_group_exceeds_the_fan_in(spark):
    """One group with nearly all blobs, many with one, and null blobs: rounds follow from the counts."""
    from splitcount.operators.codec import Sketch, merge

    blob = lambda i: Sketch.from_pairs(6, [i % 64, i * 7 % 64], [1 + i % 9, 2 + i % 5]).to_bytes()
    rows = [("hot", blob(i)) for i in range(700)] + [(f"g{i}", blob(i)) for i in range(40)] + [("none", None), ("hot", None)]
    df = spark.createDataFrame(rows, "g string, sketch binary").repartition(6)
    rounds = [max(r["count"] for r in x.groupBy("g", "_salt").count().collect()) for x in A.merge_rounds(df, ["g"], fan_in=8)]
    assert len(rounds) >= 3 and max(rounds) <= 8
    got = {r["g"]: r["sketch"] for r in A.merge_sketches(df, ["g"], fan_in=8).collect()}
    want = {g: merge([Sketch.from_bytes(b) for k, b in rows if k == g and b]).to_bytes() for g in got if g != "none"}
    assert got.pop("none") is None and {g: bytes(b) for g, b in got.items()} == want and len(want) == 41


def test_form_follows_the_input(spark):
    """A wide global count over much input goes by blobs, many small groups by registers; both are lossless under every variant."""
    from splitcount.plans.choose import input_figures

    big = spark.range(10**9).select(F.col("id").cast("string").alias("v"), F.pmod("id", F.lit(10**6)).alias("g"))
    assert choose_form(10, *input_figures(big, [])) == "partial"
    assert choose_form(10, *input_figures(big, ["g"], 10**8)) == "relational"
    df = items(spark, 4000, 3).repartition(4)
    for variant in ("opt", "lazy", "min"):
        forms = [{r["g"]: r["e"] for r in A.distinct_sketch(df, ["g"], "v", 6, variant=variant, form=f).select("g", A.sketch_estimate("sketch").alias("e")).collect()} for f in ("relational", "partial")]
        tags = {bytes(r["sketch"])[5] for f in ("relational", "partial") for r in A.distinct_sketch(df, ["g"], "v", 6, variant=variant, form=f).collect()}
        assert forms[0] == forms[1] and tags == {VARIANT_IDS[variant]}


def test_null_and_empty_items(spark):
    df = spark.createDataFrame([("a", None), ("a", ""), ("b", None)], "g string, v string")
    assert [tuple(r)[0] for r in R.build(df, ["g"], "v", 4).collect()] == ["a"]
    none = df.limit(0)
    assert A.distinct_sketch(none, ["g"], "v", 6).count() == 0
    assert A.distinct_sketch(none, [], "v", 6).select(A.sketch_estimate("sketch")).first()[0] == 0.0


def test_store_replay_and_ranges(spark, tmp_path):
    store = SketchStore(spark, str(tmp_path / "store"), ("event_type",))
    ev = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    write = panes.publish(store, "user_id", 8)
    write(ev, 0)
    first = {(str(r["pane"]), r["event_type"]): bytes(r["sketch"]) for r in store.read().collect()}
    write(ev.where("event_id % 2 = 0"), 1)
    assert first == {(str(r["pane"]), r["event_type"]): bytes(r["sketch"]) for r in store.read().collect()}
    assert store.validate().count() == 0
    some = store.read("2024-01-05", "2024-01-06")
    assert {str(r["pane"]) for r in some.collect()} <= {"2024-01-05", "2024-01-06"}
    assert "PartitionFilters: [isnotnull(pane" in executed_plan(some)
    assert all(str(r["pane"]) <= "2024-01-10" for r in store.asof("2024-01-10").collect())


def test_generated_pairs_repeat(spark):
    pairs_source.register(spark)
    read = lambda k: sorted(map(tuple, spark.read.format("splitcount_pairs").option("n", 3000).option("slices", k).load().collect()))
    assert read(1)[:5] == sorted(map(tuple, spark.read.format("splitcount_pairs").option("n", 3000).option("slices", 1).load().collect()))[:5]
    assert len(read(3)) == 3000


def test_sliding_windows_merge_panes(spark):
    rows = spark.sql("select timestamp'2024-01-01' + make_interval(0,0,0,cast(id % 5 as int)) as ts, id from range(200)")
    regs = R.build(rows.withColumnRenamed("ts", "pane"), ["pane"], F.col("id").cast("string"), 6)
    wide = panes.sliding(regs, [], "1 day", 3)
    want = R.build(rows.where("date(ts) between '2024-01-02' and '2024-01-04'"), [], F.col("id").cast("string"), 6)
    got = wide.where("pane = timestamp'2024-01-02'").select("j", "r")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_profile_covers_all_columns(spark):
    got = {r["name"]: r for r in workloads.profile(spark.read.parquet(f"{SF}/orders.parquet"), 12).collect()}
    assert len(got) == 6 and got["o_orderkey"]["est"] == pytest.approx(got["o_orderkey"]["n"], rel=0.1)


def test_entry_works_without_the_training_part(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())

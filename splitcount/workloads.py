"""Workloads of the experiments, over tables and over generated input.

Each returns a DataFrame lazily.  Generated input is seeded by hashes of ids, never by a random function,
so a re-run of a lost task makes the same rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount.functions import theory
from splitcount.functions import hashing as H
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators import split as S
from splitcount.operators.aggregate import merge_sketches, pack_registers
from splitcount.operators.baselines import exact, raising
from splitcount.operators.rivals import HEADER_BITS
from splitcount.schema import registers_of
from splitcount.session import cut, table


def ladder(start: int = 4, stop: int = 60) -> list[int]:
    """Counts at powers of the square root of two."""
    return [round(2 ** (i / 2)) for i in range(start, stop + 1)]


def integers(spark: SparkSession, n: int, rep: int = 0) -> DataFrame:
    """(v): n distinct 64-bit integers of a repetition."""
    return spark.range(n).select(F.xxhash64(F.lit(rep), "id").alias("v"))


def strings(spark: SparkSession, n: int, rep: int = 0) -> DataFrame:
    """(v): n eight-character strings; few may collide."""
    return spark.range(n).select(F.substring(F.md5(F.concat_ws(":", F.lit(rep), "id").cast("binary")), 1, 8).alias("v"))


def raw_pairs(spark: SparkSession, n: int, p: int, rep: int = 0, family: str = "xx64", ids: DataFrame | None = None) -> DataFrame:
    """(id, j, r): j uniform over m, r geometric with chance a half.

    ``xx64`` draws j and r from hashes of their own; ``md5_64`` draws both from one, as another engine can, for the
    numbers below n or for given ``ids``.
    """
    if family == "md5_64":
        return H.pairs(spark.range(n) if ids is None else ids, ["id"], F.concat(F.lit(f"{rep}:"), F.col("id").cast("string")), p)
    j = F.pmod(F.xxhash64(F.lit(2 * rep), "id"), F.lit(registers_of(p)))
    h = F.xxhash64(F.lit(2 * rep + 1), "id")
    rows = spark.range(n).select("id", j.alias("j"), F.shiftrightunsigned(h, 32).alias("hi"), h.bitwiseAND(0xFFFFFFFF).alias("lo"))
    return rows.select("id", "j", H.rank().alias("r"))


def law_rows(spark: SparkSession, n: float, ps: list[int], rep: int = 0) -> DataFrame:
    """(p, j, r) drawn from the register law at n items, zeros absent, by hashes that another engine can repeat."""
    ids = None
    for p in ps:
        one = spark.range(registers_of(p)).select(F.lit(p).alias("p"), F.col("id").alias("j"))
        ids = one if ids is None else ids.unionByName(one)
    rows = H.with_hash(ids, F.concat(F.lit(f"{rep}:"), F.col("p").cast("string"), F.lit(":"), F.col("j").cast("string")))
    u = (F.col("hi") * F.lit(1 << 21) + F.shiftright("lo", 11) + 0.5) / F.lit(2.0**53)
    # Smallest k with (1 - 1/(m 2**k)) ** n >= u.
    k = F.ceil(F.log2(1 / (F.pow(F.lit(2.0), "p") * (1 - F.exp(F.log(u) / F.lit(float(n)))))))
    return rows.select("p", "j", F.least(F.lit(63), F.greatest(F.lit(0), k)).cast("long").alias("r")).where("r > 0")


def event_stream(spark: SparkSession, sf_dir: str, least: int) -> DataFrame:
    """(id): the ids of all events, and of as many copies with shifted ids as make ``least`` of them."""
    events = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"))
    most, n = events.agg(F.max("id"), F.count("id")).first()
    span = (most or 0) + 1
    copies = F.explode(F.sequence(F.lit(0), F.lit(max(0, -(-least // max(n, 1)) - 1)))).alias("k")
    return events.select("id", copies).select((F.col("id") + F.col("k") * F.lit(span)).alias("id"))


def sized(rows: DataFrame, value: str = "v", ps: list[int] = tuple(range(4, 19))) -> DataFrame:
    """(p, j, r): registers of every size from one fine build; a register counts for its leading bits at every p."""
    top = max(ps)
    fine = cut(R.build(rows, [], value, top))
    every = fine.select("j", "r", F.explode(F.array(*map(F.lit, ps))).alias("p"))
    return every.groupBy("p", F.call_function("shiftright", F.col("j"), F.lit(top) - F.col("p")).alias("j")).agg(F.max("r").alias("r"))


def load_changes(spark: SparkSession, ps: list[int], top_load: int, ids: DataFrame | None = None) -> DataFrame:
    """(p, load, changed): pairs of each doubling of the load n / m that still raise a register, of given ids or of numbers.

    Only the at most 64 m first rows of their kind are ordered.
    """
    out = None
    for p in ps:
        m = registers_of(p)
        ups = raising(raw_pairs(spark, m * top_load, p, 3, "md5_64", ids), "id")
        by = ups.groupBy(F.floor(F.log2((F.col("id") + 1) / m)).cast("int").alias("load")).agg(F.count("*").alias("changed"))
        one = by.select(F.lit(p).alias("p"), "load", "changed")
        out = one if out is None else out.unionByName(one)
    return out


def grid_items(spark: SparkSession, sf_dir: str, reps: int) -> DataFrame:
    """(input, rep, step, v): the three kinds of input from the tables, and fresh items in every repetition.

    Integers are order keys, strings customer names, pairs the events' ids, which stand for ranks drawn before.
    ``step`` is the first rung of the ladder that reaches the item.
    """
    step = lambda c: F.ceil(2 * F.log2(F.greatest(F.col(c), F.lit(1)))).cast("int").alias("step")
    parts = [
        table(spark, sf_dir, "lineitem").select(F.lit("integers").alias("input"), step("l_orderkey"), F.col("l_orderkey").cast("string").alias("v")),
        table(spark, sf_dir, "customer").select(F.lit("strings").alias("input"), step("c_custkey"), F.col("c_name").alias("v")),
        table(spark, sf_dir, "events").select(F.lit("pairs").alias("input"), step("event_id"), F.concat(F.lit("pair "), F.col("event_id").cast("string")).alias("v")),
    ]
    rows = parts[0].unionByName(parts[1]).unionByName(parts[2])
    rep = F.explode(F.sequence(F.lit(0), F.lit(reps - 1)))
    return rows.select("input", "step", "v", rep.alias("rep")).select("input", "rep", "step", F.concat(F.col("rep").cast("string"), F.lit(":"), F.col("v")).alias("v"))


def grid(spark: SparkSession, sf_dir: str, ps: list[int] = tuple(range(4, 19)), rungs: list[int] = tuple(range(4, 61)), reps: int = 10) -> DataFrame:
    """(p, input, rep, upto, n, est, rel_err): growing prefixes of every input and repetition, for every p.

    One fine build for all: a register's history is a running maximum over prefix steps, and coarser
    sketches fold from the finest.
    """
    top = max(ps)
    keys = ["input", "rep"]
    items = grid_items(spark, sf_dir, reps)
    fine = R.build(items, [*keys, "step"], "v", top)
    upto = F.broadcast(spark.createDataFrame([(r,) for r in rungs], "upto int"))
    every = cut(R.from_pairs(fine.join(upto, F.col("step") <= F.col("upto")), [*keys, "upto"]))
    truth = items.distinct().groupBy(*keys, "step").agg(F.count("*").alias("_n"))
    truth = cut(truth.join(upto, F.col("step") <= F.col("upto")).groupBy(*keys, "upto").agg(F.sum("_n").alias("n")))
    # All sizes in one pass: a register of the finest sketch counts for its leading bits at every p.
    sized = every.select(*keys, "upto", "r", "j", F.explode(F.array(*map(F.lit, ps))).alias("p"))
    folded = sized.groupBy(*keys, "upto", "p", F.call_function("shiftright", F.col("j"), F.lit(top) - F.col("p")).alias("j")).agg(F.max("r").alias("r"))
    m = F.pow(F.lit(2.0), "p")
    per = folded.groupBy(*keys, "upto", "p").agg((F.sum(F.pow(F.lit(2.0), -F.col("r"))) + (F.pow(F.lit(2.0), F.col("p")) - F.count("*"))).alias("s"), (F.pow(F.lit(2.0), F.col("p")).cast("long") - F.count("*")).alias("v"))
    scale = F.create_map(*(F.lit(x) for p in ps for x in (p, E.alpha(p) * registers_of(p) ** 2)))
    e = F.element_at(scale, F.col("p")) / F.col("s")
    est = F.when((e <= 2.5 * m) & (F.col("v") > 0), m * F.log(m / F.col("v"))).when(e > 2.0**64 / 30, F.lit(-(2.0**64)) * F.log(1 - e / 2.0**64)).otherwise(e)
    got = per.select("p", *keys, "upto", F.round(est, 4).alias("est")).join(truth, [*keys, "upto"])
    return got.select("p", *keys, "upto", "n", "est", F.round(F.col("est") / F.col("n") - 1, 6).alias("rel_err"))


def sizes_at(spark: SparkSession, n: float = 2.0**30, ps: list[int] = tuple(range(4, 19)), rep: int = 0, kappa: int = 3, regs: DataFrame | None = None) -> DataFrame:
    """(p, variant, bits, per_register, reduction) of every implementation at n items, by given or by sampled registers.

    The bit matrix stands at the sum of its column entropies, by their law.
    """
    hist = cut(S.histograms(law_rows(spark, n, ps, rep) if regs is None else regs))
    windows = cut(S.windows(hist, ["p"], kappa))
    low = F.min("r").over(W.partitionBy("p"))
    above = hist.withColumn("low", low).groupBy("p").agg(F.sum(F.when(F.col("r") - F.col("low") >= 15, F.col("c")).otherwise(0)).cast("long").alias("sparse"))
    m, entry = F.pow(F.lit(2.0), "p").cast("long"), F.col("p") + 6
    forms = [
        ("split_opt", S.widest(windows, ["p"]), kappa * m + F.col("sparse") * entry),
        ("split_lazy", S.climbed(windows, ["p"]), kappa * m + F.col("sparse") * entry),
        ("split_min", S.lowest(windows, ["p"]), kappa * m + F.col("sparse") * entry),
        ("reg4", above, 4 * m + F.col("sparse") * entry),
        ("reg6", above, 6 * m),
        ("reg6_library", above, 6 * m + HEADER_BITS),
        ("reg8", above, 8 * m),
    ]
    out = None
    for name, rows, bits in forms:
        one = rows.select("p", F.lit(name).alias("variant"), bits.cast("long").alias("bits"))
        out = one if out is None else out.unionByName(one)
    f = -F.expm1(F.lit(-float(n)) / F.pow(F.lit(2.0), F.col("p") + F.col("k")))
    h = F.when((f <= 0) | (f >= 1), 0.0).otherwise(-f * F.log2(f) - (1 - f) * F.log2(1 - f))
    cells = hist.select("p").distinct().select("p", F.explode(F.sequence(F.lit(1), F.lit(63))).alias("k"))
    matrix = cells.groupBy("p").agg(F.round(F.sum(h) * F.pow(F.lit(2.0), F.first("p"))).cast("long").alias("bits"))
    out = out.unionByName(matrix.select("p", F.lit("matrix").alias("variant"), "bits"))
    per = F.col("bits") / m
    return out.select("p", "variant", "bits", F.round(per, 6).alias("per_register"), F.round(1 - per / 6, 6).alias("reduction"))


def closed_sizes(spark: SparkSession, n: float = 2.0**30, kappa: int = 3) -> DataFrame:
    """(p, per_register, reduction, entropy) for p = 4..18 in closed form."""
    rows = [(p, x := theory.expected_bits(n, p, kappa) / registers_of(p), 1 - x / 6, theory.entropy(n, p)) for p in range(4, 19)]
    return spark.createDataFrame(rows, "p int, per_register double, reduction double, entropy double")


def halves(df: DataFrame, value: str, p: int) -> tuple[DataFrame, DataFrame]:
    """Registers of two disjoint halves of the items."""
    side = F.pmod(F.xxhash64(F.lit(5), value), F.lit(2))
    part = lambda x: R.build(df.where(side == x), [], F.col(value).cast("string"), p)
    return part(0), part(1)


def merge_check(df: DataFrame, value: str, p: int) -> DataFrame:
    """(mismatches): merged halves against the single pass."""
    merged = R.merge(*halves(df, value, p), []).withColumnRenamed("r", "r2")
    both = R.build(df, [], F.col(value).cast("string"), p).join(merged, "j", "full_outer")
    return both.agg(F.coalesce(F.sum((~F.col("r").eqNullSafe(F.col("r2"))).cast("long")), F.lit(0)).alias("mismatches"))


def outlier_flags(spark: SparkSession, n: float, p: int, delta: float, reps: int = 200) -> DataFrame:
    """(rep, x, y): whether registers 0 and 1 lie outside the window, per repetition of n pairs."""
    rows = None
    m = registers_of(p)
    centre = theory.log2(n / m)
    items = spark.range(int(n)).crossJoin(F.broadcast(spark.range(reps).select(F.col("id").alias("rep"))))  # fan-out by repetition
    h1, h2 = F.xxhash64(F.lit(1), "rep", "id"), F.xxhash64(F.lit(2), "rep", "id")
    rows = items.select("rep", F.pmod(h1, F.lit(m)).alias("j"), F.shiftrightunsigned(h2, 32).alias("hi"), h2.bitwiseAND(0xFFFFFFFF).alias("lo")).where("j < 2")
    regs = R.from_pairs(rows.select("rep", "j", H.rank().alias("r")), ["rep"])
    out = lambda j: F.max(F.when((F.col("j") == j) & (F.abs(F.col("r") - centre) < delta), 0.0).when(F.col("j") == j, 1.0))
    return regs.groupBy("rep").agg(F.coalesce(out(0), F.lit(1.0)).alias("x"), F.coalesce(out(1), F.lit(1.0)).alias("y"))


def profile(df: DataFrame, p: int = 12) -> DataFrame:
    """(name, n, est) for every column in one scan; n is the exact count beside it."""
    stacked = F.explode(F.array(*(F.struct(F.lit(f.name).alias("name"), H.canon(f.name, f.dataType).alias("v")) for f in df.schema.fields)))
    rows = df.select(stacked.alias("x")).select("x.name", "x.v")
    est = E.from_registers(R.build(rows, ["name"], "v", p), ["name"], p).select("name", F.round("est", 4).alias("est"))
    return exact(rows, ["name"], "v").join(est, "name").select("name", "n", "est")


def neighbourhood(edges: DataFrame, p: int, hops: int = 3) -> DataFrame:
    """(g, sketch): per left node, a sketch of the right nodes within ``hops`` (odd) steps of a bipartite graph.

    Each hop joins the edges with one packed sketch for each node of the side before, so an edge carries about half
    a byte for each register; merging goes in rounds of bounded fan-in, so a hub's sketches never meet in one task.
    """
    if hops % 2 == 0:
        raise ValueError("an odd number of hops ends on the right side")
    blobs = cut(pack_registers(R.build(edges, ["a"], F.col("b").cast("string"), p), ["a"], p))
    for _ in range(hops // 2):
        right = cut(merge_sketches(edges.join(blobs, "a").select("b", "sketch"), ["b"]))
        blobs = cut(merge_sketches(edges.join(right, "b").select("a", "sketch"), ["a"]))
    return blobs.select(F.col("a").alias("g"), "sketch")

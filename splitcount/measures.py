"""Timed measures of the experiments, as DataFrames of their records.

Build times of whole jobs are medians of repetitions over the noop sink; sequential runs are timed inside their
tasks, under a monotonic clock.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from statistics import median

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount import workloads as Wk
from splitcount.functions import theory
from splitcount.functions.hashing import GOLDEN_HI, GOLDEN_LO, pairs, with_hash
from splitcount.operators import baselines as B
from splitcount.operators import registers as R
from splitcount.operators import split as S
from splitcount.operators.codec import CodedTrace, Sketch, Trace, decoded_registers, merge
from splitcount.operators.rivals import BitMatrix, FourBitOffsets, PlainRegisters
from splitcount.plans.choose import plan_stats as _plan_stats
from splitcount.schema import P_MAX, registers_of
from splitcount.session import cut

RECORD = "variant string, p int, n long, seconds double, per_item double, bits long, est double"


def run_time(make: Callable[[], DataFrame], reps: int = 3) -> float:
    def once() -> float:
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        return time.perf_counter() - t

    return median(once() for _ in range(reps))


def builds(spark: SparkSession, n: int, p: int) -> dict[str, Callable[[], DataFrame]]:
    """Ways to count n generated integers: ours up to the base search, and the built-in ones."""
    ints = Wk.integers(spark, n)
    regs = lambda: R.build(ints, [], "v", p, family="xx64")
    return {
        "reg6": regs,
        "split_opt": lambda: S.best_base(S.histogram(regs(), [], p), [], p),
        "split_min": lambda: S.min_base(S.histogram(regs(), [], p), []),
        "pairs": lambda: R.from_pairs(Wk.raw_pairs(spark, n, p).select("j", "r"), []),
        "builtin_improved": lambda: ints.agg(F.approx_count_distinct("v", max(0.005, theory.rse(p)))),
        "builtin_sketch": lambda: B.builtin_sketch(ints, [], "v", min(p, 21)),
    }


def update_time(spark: SparkSession, n: int, p: int = 15, reps: int = 3) -> DataFrame:
    """(variant, p, n, seconds, per_item): build time, also per distinct item."""
    rows = [(k, p, n, s := run_time(f, reps), s / n, None, None) for k, f in builds(spark, n, p).items()]
    return spark.createDataFrame(rows, RECORD)


def total_time(spark: SparkSession, n: int, ps: list[int], reps: int = 1) -> DataFrame:
    """Build time at a fixed count, over the number of registers."""
    rows = [(k, p, n, s := run_time(f, reps), s / n, None, None) for p in ps for k, f in builds(spark, n, p).items()]
    return spark.createDataFrame(rows, RECORD)


def stream(kind: str, p: int, n: int, rep: int):
    """Seeded input of one sequential run, and how an item of it becomes (j, r).

    ``pairs``: given as they are; ``integers``: 64-bit numbers, mixed; ``strings``: eight characters, hashed.
    """
    import numpy as np
    import xxhash

    rng = np.random.default_rng([rep, p, n])
    if kind == "pairs":
        return list(zip(rng.integers(0, registers_of(p), n).tolist(), np.minimum(rng.geometric(0.5, n), 63).tolist(), strict=True)), None
    if kind == "integers":
        items, digest = rng.integers(0, 1 << 63, n, dtype=np.uint64).tolist(), lambda x: xxhash.xxh64_intdigest(x.to_bytes(8, "little"))
    else:
        letters = rng.integers(48, 123, (n, 8), dtype=np.uint8).tobytes()
        items, digest = [letters[k : k + 8] for k in range(0, 8 * n, 8)], xxhash.xxh64_intdigest
    return items, _paired(digest, p)


def _paired(digest, p: int):
    """How an item becomes (j, r)."""
    golden = GOLDEN_HI << 32 | GOLDEN_LO

    def pair(x) -> tuple[int, int]:
        h = digest(x)
        return (h * golden & (1 << 64) - 1) >> (64 - p), min(63, 65 - h.bit_length())

    return pair


def stream_of(rows: pd.DataFrame, kind: str, p: int):
    """The same from a table's rows (id, j at the finest size, r), in the order of their ids."""
    import xxhash

    rows = rows.sort_values("id")
    if kind == "pairs":
        return list(zip((rows["j"].to_numpy() >> (P_MAX - p)).tolist(), rows["r"].tolist(), strict=True)), None
    if kind == "integers":
        return rows["id"].tolist(), _paired(lambda x: xxhash.xxh64_intdigest(x.to_bytes(8, "little")), p)
    return [str(x).encode() for x in rows["id"].tolist()], _paired(xxhash.xxh64_intdigest, p)


def contender(variant: str, p: int):
    """An empty sketch of each implementation."""
    makers = {
        "zstd": lambda: CodedTrace(p),
        "reg6": lambda: PlainRegisters(p),
        "reg8": lambda: PlainRegisters(p, 8),
        "reg6_library": lambda: PlainRegisters(p, 6, True),
        "reg4": lambda: FourBitOffsets(p),
        "matrix": lambda: BitMatrix(p),
    }
    return makers[variant]() if variant in makers else Trace(p, variant=variant)


CONTENDERS = ("opt", "lazy", "min", "zstd", "reg6", "reg8", "reg6_library", "reg4", "matrix")


def estimate_of(sketch) -> float:
    if isinstance(sketch, BitMatrix):
        return sketch.estimate()
    regs = decoded_registers(sketch.data, sketch.p) if isinstance(sketch, CodedTrace) else sketch.regs if isinstance(sketch, Trace) else sketch.registers()
    return Sketch.from_registers(regs).estimate()


def traced(p: int, n: int, variant: str, seed: int = 0, kind: str = "pairs", given=None):
    """One sequential run over seeded or given input: (sketch, seconds).  ``hash`` only hashes."""
    items, pair = given or stream(kind, p, n, seed)
    t = None if variant == "hash" else contender(variant, p)
    start = time.perf_counter()
    if t is None:
        for x in items:
            pair(x)
    elif pair is None:
        for j, r in items:
            t.offer(j, r)
    else:
        for x in items:
            t.offer(*pair(x))
    return t, time.perf_counter() - start


RUN = "variant string, p int, n long, rep int, input string, seconds double, per_item double, bits long, est double, changed long, compress_calls long, rebases long"


def _record(x, given=None) -> pd.DataFrame:
    t, s = traced(x.p, x.n, x.variant, x.rep, x.input, given)
    bits = None if t is None else 8 * len(t.data) if isinstance(t, CodedTrace) else t.bits
    c = t.counters if isinstance(t, Trace) else None
    counts = [c.changed, c.compress_calls, c.rebases] if c else [None] * 3
    return pd.DataFrame([[x.variant, x.p, x.n, x.rep, x.input, s, s / x.n, bits, None if t is None else estimate_of(t), *counts]], columns=[f.split()[0] for f in RUN.split(", ")])


def sequential(spark: SparkSession, runs: list[tuple[str, int, int, int, str]], ids: DataFrame | None = None) -> DataFrame:
    """Sequential runs (variant, p, n, repetition, input), each timed in a task of its own.

    A run is one stream by nature; a grid of runs is what spreads over the cluster.  The same repetition gives every
    implementation the same data: seeded, or the first n of the given ids, in their order, with a hash for each repetition.
    """
    plan = spark.createDataFrame([(k, *r) for k, r in enumerate(runs)], "k int, variant string, p int, n long, rep int, input string")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for x in b.itertuples(index=False):
                yield _record(x)

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        x = next(rows.head(1).itertuples(index=False))
        if len(rows) < x.n:
            raise ValueError(f"a stream of {x.n} items was asked of {len(rows)}")
        return _record(x, stream_of(rows, x.input, x.p))

    if ids is not None:
        first = ids.orderBy("id").limit(max(r[2] for r in runs))
        first = cut(first.withColumn("at", F.row_number().over(W.orderBy("id"))))  # one stream, as long as the longest run
        reps = F.explode(F.array(*map(F.lit, sorted({r[3] for r in runs})))).alias("rep")
        items = first.select("id", "at", reps).withColumn("_v", F.concat(F.col("rep").cast("string"), F.lit(":"), F.col("id").cast("string")))
        items = pairs(items, ["id", "at", "rep"], "_v", P_MAX).join(F.broadcast(plan), "rep").where("at <= n")
        return items.groupBy("k").applyInPandas(one, RUN)
    return plan.repartitionByRange(max(1, len(runs)), "k").mapInPandas(run, RUN)


def _median(runs: DataFrame) -> DataFrame:
    by = ["variant", "p", "n", "input"]
    middle = lambda c: F.percentile(c, 0.5).alias(c)
    return runs.groupBy(*by).agg(middle("seconds"), middle("per_item"), middle("bits"), middle("est"), middle("compress_calls"))


def update_scaling(spark: SparkSession, p: int = 15, ns: list[int] = (1 << 10, 1 << 13, 1 << 16), variants=("opt", "lazy", "min", "reg6", "reg8", "reg4", "matrix"), reps: int = 3, kind: str = "integers", ids: DataFrame | None = None) -> DataFrame:
    """(variant, p, n, input, per_item, ..): update time per item as the stream grows."""
    return _median(sequential(spark, [(v, p, n, rep, kind) for v in variants for n in ns for rep in range(reps)], ids))


def total_by_registers(spark: SparkSession, n: int = 1 << 16, ps: list[int] = tuple(range(4, 19, 2)), variants=("opt", "lazy", "min", "reg6", "reg8", "reg4"), reps: int = 1, kind: str = "pairs", ids: DataFrame | None = None) -> DataFrame:
    """(variant, p, n, input, seconds, ..): time for a whole stream, over the number of registers."""
    return _median(sequential(spark, [(v, p, n, rep, kind) for v in variants for p in ps for rep in range(reps)], ids))


def load_factor(spark: SparkSession, ps: list[int] = (4, 6, 8), rungs: int = 8, variants=("opt", "lazy", "min"), reps: int = 3) -> DataFrame:
    """(variant, p, load, per_item, compress_calls): sequential time per item against the load n / m."""
    runs = [(v, p, registers_of(p) << k, rep, "pairs") for p in ps for k in range(rungs) for v in variants for rep in range(reps)]
    got = _median(sequential(spark, runs))
    return got.select("variant", "p", (F.col("n") / F.pow(F.lit(2.0), "p")).cast("long").alias("load"), "per_item", F.col("compress_calls").cast("long").alias("compress_calls"))


def merge_time(spark: SparkSession, ps: list[int] = (10, 14, 18), n: float = 2.0**30, reps: int = 5) -> DataFrame:
    """(variant, p, seconds, per_register, sparse): merging two halves in the compressed form."""
    import numpy as np

    rows = []
    for p in ps:
        m = registers_of(p)
        rng = np.random.default_rng(p)
        draw = lambda m=m, rng=rng: np.clip(np.ceil(-np.log2(-np.expm1(np.log(rng.random(m)) / (n / 2)) * m)), 0, 63).astype(np.int64)
        halves = draw(), draw()
        for v in ("opt", "lazy", "min"):
            pair = [Sketch.from_registers(x, base=int(x.min()) if v == "min" else None, variant=v) for x in halves]
            times = []
            for _ in range(reps):
                t = time.perf_counter()
                merge(pair)
                times.append(time.perf_counter() - t)
            rows.append((v, p, median(times), median(times) / m, sum(s.sparse for s in pair)))
    return spark.createDataFrame(rows, "variant string, p int, seconds double, per_register double, sparse long")


def hash_only(df: DataFrame, value: str, family: str = "md5_64", reps: int = 3) -> float:
    """Seconds to hash a column without updating anything."""
    return run_time(lambda: with_hash(df.select(value).where(F.col(value).isNotNull()), F.col(value).cast("string"), family).agg(F.sum("hi"), F.max("lo")), reps)


def tradeoff(spark: SparkSession, ps: list[int] = (8, 10, 12), n: int = 20_000, variants=("opt", "lazy", "min", "zstd", "reg6", "reg4", "matrix"), reps: int = 1) -> DataFrame:
    """(variant, p, bits, per_item): size against sequential update time, every variant over the same items."""
    got = _median(sequential(spark, [(v, p, n, rep, "pairs") for v in variants for p in ps for rep in range(reps)]))
    return got.select("variant", "p", F.col("bits").cast("long").alias("bits"), "per_item")


def front(points: DataFrame) -> DataFrame:
    """Points that no other point of the same p beats in both size and time (a few hundred rows)."""
    a = points.where("per_item is not null")
    b = a.select(F.col("p").alias("_p"), F.col("bits").alias("_b"), F.col("per_item").alias("_t"))
    beaten = (F.col("p") == F.col("_p")) & (F.col("_b") <= F.col("bits")) & (F.col("_t") <= F.col("per_item")) & ((F.col("_b") < F.col("bits")) | (F.col("_t") < F.col("per_item")))
    return a.join(F.broadcast(b), beaten, "left_anti")


def plan_stats(df: DataFrame) -> dict[str, int]:
    return _plan_stats(df)


def compare_variants(df: DataFrame, value: str, ps: list[int] = (8, 10, 12)) -> DataFrame:
    """(p, variant, b, sparse, bits): the same registers under every split rule, from one fine build."""
    top = max(ps)
    fine = R.from_pairs(pairs(df, [], F.col(value).cast("string"), top), [])
    out = None
    for p in ps:
        h = S.histogram(R.fold(fine, [], top, p), [], p)
        forms = {"opt": S.best_base(h, [], p), "min": S.base_at(h, S.min_base(h, []), [], p)}
        for name, base in forms.items():
            one = base.select(F.lit(p).alias("p"), F.lit(name).alias("variant"), "b", "sparse", "bits")
            out = one if out is None else out.unionByName(one)
    return out



"""Where queries register, and the DuckDB text that several of them share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitcount.schema import registers_of
from splitcount.session import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

P = 10
KAPPA = 3


def query(name: str, sql: str | None = None):
    """Registers a function of (spark, sf_dir) and its counterpart."""

    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# ------------------------------------------------------------------ inputs: (g, v) with v the item's text

#: Name -> (DuckDB select of g and v, Spark maker of the same).
INPUTS: dict[str, tuple[str, Callable[[SparkSession, str], DataFrame]]] = {
    "orderkeys": ("select 'all' as g, cast(l_orderkey as varchar) as v from lineitem", lambda s, d: table(s, d, "lineitem").select(F.lit("all").alias("g"), F.col("l_orderkey").cast("string").alias("v"))),
    "orderkeys_by_flag": ("select l_returnflag as g, cast(l_orderkey as varchar) as v from lineitem", lambda s, d: table(s, d, "lineitem").select(F.col("l_returnflag").alias("g"), F.col("l_orderkey").cast("string").alias("v"))),
    "cents": ("select 'all' as g, cast(cast(round(l_extendedprice * 100) as bigint) as varchar) as v from lineitem", lambda s, d: table(s, d, "lineitem").select(F.lit("all").alias("g"), cents("l_extendedprice").alias("v"))),
    "cents_by_flag": ("select l_returnflag as g, cast(cast(round(l_extendedprice * 100) as bigint) as varchar) as v from lineitem", lambda s, d: table(s, d, "lineitem").select(F.col("l_returnflag").alias("g"), cents("l_extendedprice").alias("v"))),
    "texts": ("select lang as g, text as v from documents", lambda s, d: table(s, d, "documents").select(F.col("lang").alias("g"), F.col("text").alias("v"))),
    "events": ("select event_type as g, cast(event_id as varchar) as v from events", lambda s, d: table(s, d, "events").select(F.col("event_type").alias("g"), F.col("event_id").cast("string").alias("v"))),
    "customers": ("select o_orderstatus as g, cast(o_custkey as varchar) as v from orders", lambda s, d: table(s, d, "orders").select(F.col("o_orderstatus").alias("g"), F.col("o_custkey").cast("string").alias("v"))),
}

#: The four grouped columns that the estimate queries share.
_FOUR = {"cents": "cents_by_flag", "customers": "customers", "events": "events", "texts": "texts"}
INPUTS["four"] = (
    " union all ".join(f"select '{n}:' || g as g, v from ({INPUTS[k][0]})" for n, k in _FOUR.items()),
    lambda s, d: _union([INPUTS[k][1](s, d).select(F.concat(F.lit(f"{n}:"), "g").alias("g"), "v") for n, k in _FOUR.items()]),
)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def cents(col: str):
    return F.round(F.col(col) * 100).cast("long").cast("string")


def src(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return INPUTS[name][1](spark, sf_dir)


def src_sql(name: str) -> str:
    return INPUTS[name][0]


# ------------------------------------------------------------------ DuckDB text


def index_sql(p: int) -> str:
    """Top p bits of the hash times the golden-ratio constant, in 128-bit arithmetic."""
    return f"cast(((((hi::uhugeint * 4294967296 + lo::uhugeint) * 11400714819323198485::uhugeint) % 18446744073709551616::uhugeint) // {1 << (64 - p)}::uhugeint) as bigint)"


RANK_SQL = "cast(case when hi > 0 then 33 - length(bin(hi)) else least(63, 65 - length(bin(lo))) end as bigint)"


def hash_sql(value: str = "v") -> str:
    return f"('0x' || substr(md5({value}), 1, 8))::bigint as hi, ('0x' || substr(md5({value}), 9, 8))::bigint as lo"


def with_pairs(select: str, p: int = P, tag: str = "", cols: str = "g") -> str:
    """CTEs hashed, pairs: (cols, j, r) of a select that gives cols and v."""
    return f"""hashed{tag} as (select {cols}, {hash_sql()} from ({select}) where v is not null),
pairs{tag} as (select {cols}, {index_sql(p)} as j, {RANK_SQL} as r from hashed{tag})"""


def with_regs(select: str, p: int = P, tag: str = "", cols: str = "g") -> str:
    return with_pairs(select, p, tag, cols) + f",\nregs{tag} as (select {cols}, j, max(r) as r from pairs{tag} group by {cols}, j)"


def with_hist(select: str | None, p: int = P, tag: str = "", cols: str = "g") -> str:
    head = with_regs(select, p, tag, cols) + ",\n" if select else ""
    m = registers_of(p)
    return (
        head
        + f"""hist{tag} as (
  select {cols}, r, count(*) as c from regs{tag} group by {cols}, r
  union all
  select {cols}, cast(0 as bigint) as r, {m} - count(*) as c from regs{tag} group by {cols} having count(*) < {m})"""
    )


def with_base(select: str | None, p: int = P, kappa: int = KAPPA, tag: str = "", cols: str = "g", hist: bool = True) -> str:
    head = with_hist(select, p, tag, cols) + ",\n" if hist else ""
    m = registers_of(p)
    on = " and ".join(f"a.{c.strip()} = h.{c.strip()}" for c in cols.split(","))
    named = ", ".join(f"a.{c.strip()}" for c in cols.split(","))
    return (
        head
        + f"""cand{tag} as (
  select {named}, a.r as b, cast(sum(h.c) as bigint) as dense
  from hist{tag} a join hist{tag} h on {on} and h.r between a.r and a.r + {(1 << kappa) - 1} group by {named}, a.r),
base{tag} as (
  select {cols}, b, dense, {m} - dense as sparse, cast({kappa * m} + ({m} - dense) * {p + 6} as bigint) as bits
  from (select *, row_number() over (partition by {cols} order by dense desc, b) as n from cand{tag}) where n = 1)"""
    )


def alpha_of(p: int) -> float:
    from splitcount.operators.estimate import alpha

    return alpha(p)


ALL_P = tuple(range(4, 19))


def sizes_sql() -> str:
    """(p, m, alpha m m) of every size."""
    return "(values " + ", ".join(f"({p}, {float(registers_of(p))!r}, {alpha_of(p) * registers_of(p) ** 2!r})" for p in ALL_P) + ") sizes(p, m, am)"


def with_sized(select: str) -> str:
    """CTEs n, regs and sized: the distinct items of a select of g and v, and its registers (p, m, am, j, r) at every size."""
    return f"n as (select count(distinct v) as n from ({select})), {with_regs(select, 18)},\nsized as (select p, m, am, j >> (18 - p) as j, max(r) as r from regs, {sizes_sql()} group by all)"


def with_moments(p: int = P, tag: str = "", cols: str = "g") -> str:
    return f"moments{tag} as (select {cols}, sum(c * pow(2.0, -r)) as s, cast(coalesce(sum(case when r = 0 then c end), 0) as bigint) as v from hist{tag} group by {cols})"


def est_sql(p: int = P, range_bits: int | None = 64) -> str:
    """The piecewise estimate over s and v."""
    m = registers_of(p)
    e = f"({alpha_of(p) * m * m!r} / s)"
    large = f"when {e} > {2.0**range_bits / 30!r} then {-(2.0**range_bits)!r} * ln(1 - {e} / {2.0**range_bits!r})" if range_bits else ""
    return f"case when {e} <= {2.5 * m!r} and v > 0 then {float(m)!r} * ln({float(m)!r} / v) {large} else {e} end"


def with_est(select: str, p: int = P, tag: str = "", cols: str = "g") -> str:
    """CTEs up to est: (cols, v, est) rounded to four decimals."""
    return with_hist(select, p, tag, cols) + ",\n" + with_moments(p, tag, cols) + f",\nest{tag} as (select {cols}, v, round({est_sql(p)}, 4) as est from moments{tag})"

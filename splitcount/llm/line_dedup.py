"""Repeated-line removal from a suffix array over line-id sequences (DataFrame functions only).

The corpus is one sequence of lines, document after document, with a break at every document's end;
lines without a word are not part of it.  A line's id is a pair of 64-bit hashes.  Prefix doubling
names the blocks of 1, 2, 4, ... lines: the name of a block is the place of its pair of half-size names
in a global sort of the distinct pairs, so names compare like the blocks themselves, and equal names are
the stretch of the suffix array whose common prefix is that block: a longest-common-prefix interval.
Positions whose block occurs once are dropped at each step; the doubling ends when no block repeats.

Exact lengths come from the same names, downwards.  A position stands in the interval of its largest block
that an earlier position shares.  Each further step, with half the lines, cuts the intervals by the next
name: positions that share the longer block with an earlier one go on in the narrower interval, the others
stay with the first position of each narrower one.  At the end every position holds the length of the
longest run from it on that also starts earlier (``run``); runs that no line before them extends are the
maximal repeated runs, and their lines are the later copies.

A line goes if it has ``min_words`` words or more and an equal line occurs earlier, or if it lies in a
run of ``min_lines`` lines or more that occurs earlier.

Distinct blocks are counted before they are sorted, with map-side combination, and joined back; names that
hold more than a 500th of the positions (fewer than 500 names), and more than 1,000, are joined by broadcast, so
that a line that a third of all documents share is dealt like any other.  Levels without such a name take one
plain join: each step of a plan costs the driver threads and buffers, however few rows it has.

Defined results: a null text stays null and an empty one empty; rows that repeat both doc_id and text are
one document and get one answer; rows that share only the doc_id are told apart by their text; null
doc_ids come first.  An empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount.llm.common import WORD, cut

_HAS_WORD = r"[^\x20\x09-\x0D]"
_NO_ID = -(1 << 63)
#: A name is hot from this share of all named positions; fewer names than this can be.
_HOT_SHARE = 500
#: With no more rows than this a name is no load for one task, whatever its share.
_HOT_ROWS = 1000


def _doc_key(id_col: str, text_col: str) -> list[Column]:
    return [F.coalesce(F.col(id_col).cast("long"), F.lit(_NO_ID)).alias("d"), F.xxhash64(F.col(text_col)).alias("t")]


def line_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(d, t, i, at, h1, h2, words): i counts the lines that have a word, at counts all lines."""
    lines = F.transform(F.split(F.col(text_col), "\n"), lambda s, at: F.struct(at.alias("at"), s.alias("s")))
    lines = F.filter(lines, lambda x: x["s"].rlike(_HAS_WORD))
    d, t = _doc_key(id_col, text_col)
    # Generated code puts off deterministic columns until they are read, which is once for every line; a hash that
    # names its partition counts as not deterministic and is taken once for the text.
    t = F.when(F.spark_partition_id() >= 0, t).alias("t")
    rows = docs.where(F.col(text_col).isNotNull()).select(d, t, lines.alias("lines")).select("d", "t", F.posexplode("lines").alias("i", "x"))
    s = F.col("x.s")
    return rows.select("d", "t", F.col("i").cast("long").alias("i"), F.col("x.at").alias("at"), F.xxhash64(s).alias("h1"), F.xxhash64(F.lit("line"), s).alias("h2"), F.regexp_count(s, F.lit(WORD)).alias("words"))


def _hot(most: int | None, total: int | None) -> bool:
    return bool(total) and most * _HOT_SHARE > total and most > _HOT_ROWS


def _load(groups: DataFrame) -> tuple[int | None, int | None]:
    """All positions and those of the largest name, of a written table of groups; nulls if it is empty."""
    return tuple(groups.agg(F.sum("n"), F.max("n")).first())


def _with(rows: DataFrame, groups: DataFrame, on: list[str], total: int | None) -> DataFrame:
    """``rows`` joined with one row per key.

    ``total`` is the sum of the groups' counts ``n`` if some key is hot: hot keys are broadcast, the others shuffled.
    """
    if total is None:
        return rows.join(groups.drop("n"), on)
    hot = (F.col("n") * _HOT_SHARE > total) & (F.col("n") > _HOT_ROWS)
    few = groups.where(hot)  # fewer than _HOT_SHARE rows
    cold = rows.join(F.broadcast(few.select(*on)), on, "left_anti").join(groups.where(~hot).drop("n"), on)
    return rows.join(F.broadcast(few.drop("n")), on).unionByName(cold)


def _spread(rows: DataFrame, groups: DataFrame, on: list[str], ask: bool = True) -> DataFrame:
    """:func:`_with` of groups that are not written yet; without ``ask`` none of them can be hot."""
    if not ask:
        return _with(rows, groups, on, None)
    total, most = _load(groups := cut(groups))
    return _with(rows, groups, on, total if _hot(most, total) else None)


@dataclass
class Level:
    """Positions whose block of 2^k lines repeats: (d, t, i, p, name, first); ``hot`` if one block has more than its share of them."""

    rows: DataFrame
    hot: bool


def _named(rows: DataFrame, on: list[str]) -> Level | None:
    """``rows`` of the keys that occur at two positions or more, with the key's name and its first position."""
    groups = rows.groupBy(*on).agg(F.count("*").alias("n"), F.min("p").alias("first")).where("n > 1")
    groups = cut(groups.orderBy(*on).withColumn("name", F.monotonically_increasing_id()))
    total, most = _load(groups)
    if not total:
        return None
    hot = _hot(most, total)
    return Level(cut(_with(rows, groups, on, total if hot else None).drop(*on)), hot)


def suffix_levels(lines: DataFrame) -> list[Level]:
    """One table per doubling step k, of positions whose 2^k lines repeat; none if no line does.

    ``p`` orders positions by document and line; ``first`` is the first position of the block; names order the blocks.
    The first table also has ``at`` and ``words``.
    """
    repeated = lines.groupBy("h1", "h2").agg(F.count("*").alias("n")).where("n > 1")
    base = _spread(lines.select("d", "t", "i", "at", "h1", "h2", "words"), repeated, ["h1", "h2"])
    # Rows that repeat a whole document are one document.
    base = base.groupBy("d", "t", "i").agg(*(F.first(c).alias(c) for c in ("at", "words", "h1", "h2")))
    base = cut(base.orderBy("d", "t", "i").withColumn("p", F.monotonically_increasing_id()))
    out, level, k = [], _named(base, ["h1", "h2"]), 0
    while level is not None:
        out.append(level)
        ahead = W.partitionBy("d", "t").orderBy("i").rangeBetween(1 << k, 1 << k)
        pairs = level.rows.select("d", "t", "i", "p", F.col("name").alias("a"), F.max("name").over(ahead).alias("b")).where("b is not null")
        level, k = _named(pairs, ["a", "b"]), k + 1
    return out


def run_lengths(levels: list[Level]) -> DataFrame:
    """(d, t, i, run): lines of the longest run from each position on that also starts earlier; only runs of a line or more.

    An interval is known by the first of its positions (``g``) and its length (``run``).  ``ask`` marks positions
    whose length is sought; the others are what those are compared with.
    """
    later = [x.rows.where("p > first") for x in levels]
    state = None
    for k in range(len(levels) - 1, -1, -1):
        if state is not None:
            state = _narrowed(state, levels[k].rows, k, levels[k + 1].hot)
        # Positions whose largest shared block has 2^k lines, and the first positions of those blocks.
        asks = later[k] if k + 1 == len(levels) else later[k].join(later[k + 1].select("p"), "p", "left_anti")
        enter = asks.select("d", "t", "i", "p", F.lit(1 << k).cast("long").alias("run"), F.col("first").alias("g"), F.lit(True).alias("ask"))
        if k:
            firsts = levels[k].rows.join(enter.select(F.col("g").alias("p")).distinct(), "p", "left_semi")
            enter = enter.unionByName(firsts.select("d", "t", "i", "p", F.lit(1 << k).cast("long").alias("run"), F.col("p").alias("g"), F.lit(False).alias("ask")))
        state = enter if state is None else state.unionByName(enter)
    return state.where("ask").select("d", "t", "i", "run")


def _narrowed(state: DataFrame, level: DataFrame, k: int, hot: bool) -> DataFrame:
    """The intervals cut by the block of 2^k lines that follows.

    All positions of an interval share a block of the level above, so none is hot unless one there is.
    """
    cols = ["d", "t", "i", "p", "run", "g", "ask"]
    after = level.select("d", "t", F.col("i").alias("_i"), F.col("name").alias("b"))
    rows = cut(state.withColumn("_i", F.col("i") + F.col("run")).join(after, ["d", "t", "_i"], "left").drop("_i"))
    key = ["run", "g", "b"]
    met = rows.where("b is not null")
    parts = met.groupBy(*key).agg(F.count("*").alias("n"), F.min("p").alias("low"), F.max(F.when(F.col("ask"), F.col("p"))).alias("last"))
    met = cut(_spread(met, parts, key, hot))
    on = met.where("last > low").select("d", "t", "i", "p", (F.col("run") + F.lit(1 << k)).alias("run"), F.col("low").alias("g"), (F.col("ask") & (F.col("p") > F.col("low"))).alias("ask"))
    stay = met.where("p = low").select(*cols).unionByName(rows.where("b is null").select(*cols))
    asked = stay.where("ask").groupBy("run", "g").agg(F.count("*").alias("n"))
    others = _spread(stay.where("not ask"), asked, ["run", "g"], hot)  # only where something is still asked
    return on.unionByName(stay.where("ask")).unionByName(others.select(*cols))


def maximal_runs(runs: DataFrame) -> DataFrame:
    """(d, t, i, run): the runs that the line before them does not extend."""
    before = F.lag(F.struct("i", "run")).over(W.partitionBy("d", "t").orderBy("i"))
    extended = (before["i"] == F.col("i") - 1) & (before["run"] == F.col("run") + 1)
    return runs.select("d", "t", "i", "run", F.coalesce(extended, F.lit(False)).alias("_e")).where("not _e").drop("_e")


def lines_to_delete(first_level: DataFrame, runs: DataFrame, min_words: int, min_lines: int) -> DataFrame:
    """(d, t, gone, longest_run): per document with later copies, the sorted places (from 0, all lines) that go."""
    rows = first_level.select("d", "t", "i", "at", "words").join(runs, ["d", "t", "i"], "left")
    back = W.partitionBy("d", "t").orderBy("i").rangeBetween(1 - min_lines, 0)
    covered = F.max(F.col("run") >= min_lines).over(back)
    gone = (F.col("run").isNotNull() & (F.col("words") >= min_words)) | F.coalesce(covered, F.lit(False))
    rows = rows.select("d", "t", "run", F.when(gone, F.col("at")).alias("at"))
    out = rows.groupBy("d", "t").agg(F.sort_array(F.collect_set("at")).alias("gone"), F.max("run").alias("longest_run"))
    return out.where("longest_run is not null")


def repeated_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = 5, min_lines: int = 4) -> DataFrame:
    """(d, t, gone, longest_run) of the documents."""
    if min_lines < 1:
        raise ValueError("min_lines must be 1 or more")
    levels = suffix_levels(line_table(docs, id_col, text_col))
    if not levels:
        return docs.sparkSession.createDataFrame([], "d long, t long, gone array<int>, longest_run long")
    return lines_to_delete(levels[0].rows, cut(run_lengths(levels)), min_words, min_lines)


def _lines_kept(df: DataFrame, text_col: str, gone_col: str) -> DataFrame:
    """``df`` with ``_kept``: the text without the lines at the places of ``gone_col``, in time linear in the text.

    The stretches between deleted lines are sliced; ``_lines`` is used twice, so the optimiser leaves the split
    in a projection of its own instead of repeating it for every stretch.
    """
    rows = df.withColumn("_lines", F.split(F.col(text_col), "\n"))
    gone = F.coalesce(F.col(gone_col), F.array().cast("array<int>"))
    starts = F.concat(F.array(F.lit(0)), F.transform(gone, lambda g: g + 1))
    ends = F.concat(gone, F.array(F.size("_lines")))
    stretches = F.zip_with(starts, ends, lambda a, b: F.slice(F.col("_lines"), a + 1, b - a))
    kept = F.when(F.size(gone) == 0, F.col(text_col)).otherwise(F.array_join(F.flatten(stretches), "\n"))
    return rows.withColumn("_kept", kept)


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """``docs`` with later copies of repeated lines deleted from the text; all rows and columns stay."""
    gone = repeated_lines(docs, id_col, text_col, **how).select(F.col("d").alias("_d"), F.col("t").alias("_t"), F.col("gone").alias("_gone"))
    # The rows' own columns travel in one struct, so that no name can clash.
    d, t = _doc_key(id_col, text_col)
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), d.alias("_d"), t.alias("_t"), F.col(text_col).alias("_text"))
    rows = _lines_kept(rows.join(gone, ["_d", "_t"], "left"), "_text", "_gone")
    return rows.select(*(F.col("_kept").alias(c) if c == text_col else F.col("_row")[c].alias(c) for c in docs.columns))


def op6_line_dedup(spark, sf_dir: str, min_words: int = 5, min_lines: int = 4) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    gone = repeated_lines(docs, min_words=min_words, min_lines=min_lines)
    d, t = _doc_key("doc_id", "text")
    rows = _lines_kept(docs.withColumns({"d": d, "t": t}).join(gone, ["d", "t"], "left"), "text", "gone")
    return rows.select(
        "doc_id",
        F.coalesce(F.size("_lines"), F.lit(0)).cast("long").alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_deleted"),
        F.coalesce("longest_run", F.lit(0)).cast("long").alias("longest_run"),
        F.coalesce(F.array_join(F.col("gone").cast("array<string>"), ","), F.lit("")).alias("deleted"),
        F.md5(F.coalesce("_kept", F.lit("")).cast("binary")).alias("text_md5"),
    )


#: For tables whose doc_ids differ: equal lines are paired, and pairs at one distance in a row are a common run.
OP6_SQL = r"""
with l as (
  select doc_id, unnest(string_split(text, chr(10))) as s, generate_subscripts(string_split(text, chr(10)), 1) - 1 as pos
  from documents where text is not null
), w as (
  select *, row_number() over (partition by doc_id order by pos) as i,
         len(regexp_extract_all(s, '[^\x20\x09-\x0D]+')) as words
  from l where regexp_matches(s, '[^\x20\x09-\x0D]')
), pairs as (
  select a.doc_id, a.i, a.pos, a.words, b.doc_id as earlier, a.i - b.i as distance
  from w a join w b on a.s = b.s and (b.doc_id < a.doc_id or (b.doc_id = a.doc_id and b.i < a.i))
), runs as (
  select *, count(*) over (partition by doc_id, earlier, distance, island) as run
  from (select *, i - row_number() over (partition by doc_id, earlier, distance order by i) as island from pairs)
), g as (
  select doc_id, pos, max(run) as run from runs group by doc_id, pos, words having max(run) >= 4 or words >= 5
), k as (
  select doc_id, list(pos order by pos) as gone from g group by doc_id
), m as (
  select doc_id, cast(max(run) as bigint) as run from runs group by doc_id
)
select d.doc_id, coalesce(len(string_split(d.text, chr(10))), 0) as n_lines, coalesce(len(k.gone), 0) as n_deleted, coalesce(m.run, 0) as longest_run,
       coalesce(array_to_string(k.gone, ','), '') as deleted,
       md5(coalesce(array_to_string(list_filter(string_split(d.text, chr(10)), lambda x, j: not list_contains(coalesce(k.gone, []), j - 1)), chr(10)), '')) as text_md5
from documents d left join k on d.doc_id = k.doc_id left join m on d.doc_id = m.doc_id
"""

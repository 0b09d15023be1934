"""Hash halves, ranks and indexes against plain integers."""

import hashlib

import pytest
from pyspark.sql import functions as F

from splitcount.functions import hashing as H

K = 0x9E3779B97F4A7C15


def rank_of(h: int) -> int:
    return 63 if not h else min(63, 65 - h.bit_length())


def mix(x: int) -> int:
    for n, k in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ x >> n) * k % 2**64
    return x ^ x >> 31


@pytest.mark.parametrize("p", [4, 10, 12, 18])
def test_md5_pairs(spark, p):
    items = [*map(str, range(500)), "", "Ünïcode ☃", "-1"]
    df = spark.createDataFrame([(x,) for x in items] + [(None,)], "v string")
    got = H.pairs(df, ["v"], F.col("v"), p).collect()
    assert len(got) == len(items)
    for row in got:
        h = int(hashlib.md5(row["v"].encode()).hexdigest()[:16], 16)
        assert (row["j"], row["r"]) == ((h * K % 2**64) >> (64 - p), rank_of(h))


def test_mix64(spark):
    ids = [*range(300), 2**62, -1, -(2**63)]
    df = spark.createDataFrame([(x,) for x in ids], "v long")
    for row in H.with_hash(df, F.col("v"), "mix64").collect():
        assert (row["hi"] << 32) + row["lo"] == mix(row["v"] % 2**64)


def test_rank_edges(spark):
    df = spark.createDataFrame([(0, 0), (0, 1), (1, 0), (2**31, 5), (0, 2**31)], "hi long, lo long")
    assert [r[0] for r in df.select(H.rank()).collect()] == [63, 63, 32, 1, 33]


def test_prefix_index_reads_disjoint_bits(spark):
    df = spark.createDataFrame([(0xFFFFFFFF, 0), (0x00000001, 0), (0, 0x80000000), (0, 0)], "hi long, lo long")
    j, r = H.prefix_index(4)
    assert [tuple(x) for x in df.select(j, r).collect()] == [(15, 1), (0, 28), (0, 29), (0, 61)]


def test_families_and_bounds(spark):
    df = spark.range(50).withColumn("v", F.col("id"))
    for family in H.FAMILIES:
        for index in H.INDEXES:
            rows = H.pairs(df, [], "v", 6, family=family, index=index, seed=3).collect()
            assert len(rows) == 50 and all(0 <= x["j"] < 64 and 1 <= x["r"] <= 63 for x in rows)
    for bad in (3, 19):
        with pytest.raises(ValueError):
            H.pairs(df, [], "v", bad)


def test_canonical_forms(spark):
    row = spark.sql("select timestamp'2024-01-01 00:00:01' as t, date'1970-01-02' as d, true as b, cast(1.25 as decimal(5,2)) as x, array(1, 2) as a")
    got = row.select(*(H.canon(f.name, f.dataType).alias(f.name) for f in row.schema.fields)).first()
    assert tuple(got) == ("1704067201000000", "86400000000", "1", "125", "[1,2]")

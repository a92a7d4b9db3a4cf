"""Composed joins against plain ones."""

from pyspark.sql import functions as F

from ucqlearn.operators.joins import asof_join, range_join, salted_join


def same(a, b):
    b = b.select(a.columns)
    return a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_salted_join(spark):
    big = spark.range(3000).select(F.when(F.col("id") < 2000, 1).otherwise(F.col("id") % 7).cast("int").alias("k"), "id")
    big = big.union(big.limit(50)).union(spark.createDataFrame([(None, -1)], "k int, id long"))
    small = spark.createDataFrame([(1, "a"), (1, "b"), (2, "c"), (9, "d"), (None, "e")], "k int, v string")
    assert same(salted_join(big, small, "k", 500, 4), big.join(small, "k"))
    assert salted_join(big.where("false"), small, "k", 5).count() == 0


def test_asof_join(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 9, 2), ("b", 1, 3), ("c", 4, 4), ("a", 5, 1)], "u string, t int, n int")
    right = spark.createDataFrame([("a", 5, "x"), ("a", 7, "y"), ("b", 2, "z"), ("c", 1, None), ("c", 0, "w")], "u string, t int, v string")
    got = sorted(tuple(r) for r in asof_join(left, right, "u", "t", "v").collect() if r.u != "b")
    assert got == [("a", 5, 1, "x"), ("a", 5, 1, "x"), ("a", 9, 2, "y"), ("c", 4, 4, "w")]
    assert asof_join(left, right, "u", "t", "v").where("u = 'b'").first().v is None


def test_range_join(spark):
    points = spark.range(-50, 200).select((F.col("id") / 2).alias("p"))
    ranges = spark.createDataFrame([(0.0, 10.0, 1), (3.5, 3.5, 2), (9.0, 80.0, 3), (-30.0, -5.0, 4), (5.0, 1.0, 5)], "lo double, hi double, n int")
    plain = points.join(ranges, (F.col("lo") <= F.col("p")) & (F.col("p") < F.col("hi")))
    assert same(range_join(points, ranges, "p", "lo", "hi", 7.0), plain)

"""Worked examples and properties of the column functions."""

import itertools

import pytest
from pyspark.sql import functions as F

from saferoute.functions import bounds, keywords, weather

L = F.lit


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first()["x"]


def test_interpolation_example(spark):
    assert one(spark, weather.idw(L(30.0), L(20.0), L(0.2))) == pytest.approx(28)


def test_keyword_example(spark):
    assert one(spark, keywords.keyword_blocked(F.array(L(2)), F.array(L(1), L(2))))
    assert not one(spark, keywords.keyword_blocked(F.array(L(3)), F.array(L(1), L(2))))


def test_pivot_example(spark):
    u, v = (F.array(*[L(x).cast("long") for x in p]) for p in ((13, 7), (10, 20)))
    assert one(spark, bounds.lb_dist(u, v)) == 13


def test_bitmap_is_exact_and_hash_is_verified(spark):
    kw, s = F.array(L(3), L(70)), F.array(L(70))
    assert one(spark, keywords.bits_hit(keywords.bitmap(kw, 2), keywords.bitmap(s, 2)))
    assert not one(spark, keywords.bits_hit(keywords.bitmap(F.array(L(6)), 2), keywords.bitmap(s, 2)))
    a, b = F.array(L(1)), F.array(L(2))  # one bit: both collide
    hit = keywords.bits_hit(keywords.bitmap(a, 1, "hashed", 1), keywords.bitmap(b, 1, "hashed", 1))
    assert one(spark, hit)
    assert not one(spark, keywords.blocked_by_bits(a, keywords.bitmap(a, 1, "hashed", 1), b, keywords.bitmap(b, 1, "hashed", 1), "hashed"))


def grid(spark):
    values, confs = (0.0, 49.0, 50.0, 51.0, 90.0), (0, 30, 70, 100)
    rows = [(a, p, b, q) for a, b in itertools.product(values, values) for p, q in itertools.product(confs, confs)]
    return spark.createDataFrame(rows, "wj double, pj int, wk double, pk int")


def test_worlds_sum_to_one(spark):
    x = grid(spark).select(F.aggregate(weather.worlds(*map(F.col, ("wj", "pj", "wk", "pk")), L(0.3)), L(0).cast("long"), lambda a, w: a + w["prob"]).alias("p"))
    assert x.where("p <> 10000").isEmpty()


def test_bound_is_never_below_the_exact_probability(spark):
    ends = tuple(map(F.col, ("wj", "pj", "wk", "pk")))
    x = grid(spark).withColumn("f", F.explode(F.sequence(L(0), L(100)))).withColumn("f", F.col("f") / 100)
    x = x.select(weather.ub_prob_ok(*ends, L(50.0)).alias("ub"), (10000 - weather.p_exceeds(*ends, F.col("f"), L(50.0))).alias("ok"))
    assert x.where("ub < ok").isEmpty()


def test_policies_of_the_unknown_world(spark):
    p = [one(spark, weather.p_exceeds(L(60.0), L(50), L(60.0), L(50), L(0.5), L(50.0), u)) for u in (0.0, 1.0, 0.25)]
    assert p == [7500, 10000, 8125]


def test_equality_is_not_over_and_alpha_is_reached(spark):
    arr = lambda x: F.array_repeat(x, 24)
    blocked = lambda w, p, a: one(spark, weather.trip_blocked(arr(L(w)), arr(L(p)), arr(L(w)), arr(L(p)), L(480), L(10), L(50.0), L(a)))
    assert not blocked(50.0, 100, 50)  # equal to the limit
    assert blocked(51.0, 50, 75) and not blocked(51.0, 50, 76)  # P = 1 - 0.25, exactly alpha blocks


def test_python_and_column_trips_agree(spark):
    import random

    rng = random.Random(5)
    cases = []
    for _ in range(400):
        ends = [([rng.choice([10.0, 40.0, 50.0, 60.0, 95.0]) for _ in range(24)], [rng.choice([0, 20, 50, 80, 100]) for _ in range(24)]) for _ in range(2)]
        cases.append((*ends[0], *ends[1], rng.randrange(0, 3000), rng.randrange(1, 200), rng.choice([20.0, 50.0, 90.0]), rng.choice([10, 50, 75, 90])))
    df = spark.createDataFrame(cases, "tw array<double>, tp array<int>, hw array<double>, hp array<int>, t0 long, w long, eps double, alpha int")
    got = [r[0] for r in df.select(weather.trip_blocked(*map(F.col, ("tw", "tp", "hw", "hp", "t0", "w", "eps", "alpha")))).collect()]
    assert got == [weather.py_trip_blocked((a, b), (c, d), *rest) for a, b, c, d, *rest in cases]

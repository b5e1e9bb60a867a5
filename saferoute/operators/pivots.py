"""Pivots: distances, quality of a pivot set, and ways to choose one."""

from __future__ import annotations

import random
from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bounds import lb_dist
from ..sources.networks import Network
from .graph import distances
from .storage import stored


def fixed_pivots(net: Network, d: int = 5) -> list[int]:
    """Evenly spread over the vertex numbers; for runs that must not depend on a choice."""
    n = net.vertices.count()
    return sorted({i * n // d for i in range(d)})


def pivot_distances(net: Network, pivots: list[int], only: DataFrame | None = None) -> DataFrame:
    """v and piv: distances by length to the pivots, in their order; -1 where one isn't reached, no row where none is.

    ``only``: the vertices (v) that rows are asked for."""
    spark = net.vertices.sparkSession
    dist = distances(net.arcs, spark.createDataFrame([(p,) for p in pivots], "src long"), vertices=net.vertices, only=only)
    far = F.lit(-1).cast("long")
    if len(pivots) <= 32:  # a column each
        return stored(dist.groupBy("v").agg(F.array(*[F.coalesce(F.max(F.when(F.col("src") == p, F.col("dist"))), far) for p in pivots]).alias("piv")))
    rows = dist.groupBy("v").agg(F.map_from_entries(F.collect_list(F.struct("src", "dist"))).alias("m"))
    return stored(rows.select("v", F.array(*[F.coalesce(F.element_at("m", F.lit(p).cast("long")), far) for p in pivots]).alias("piv")))


def drawn(spark: SparkSession, n: int, pairs: int, seed: int) -> DataFrame:
    """u, w: ``pairs`` ordered pairs of the numbers below n, drawn by hash, less those of a number with itself."""
    return spark.range(pairs).select(*[F.pmod(F.xxhash64("id", F.lit(x), F.lit(seed)), F.lit(n)).alias(x) for x in ("u", "w")]).where("u <> w")


def drawn_pairs(piv: DataFrame, pairs: int, seed: int, n: int | None = None) -> DataFrame:
    """pu, pv: pivot distances of drawn pairs of vertices, which are numbered from 0; n: how many there are, None for one of each row."""
    draw = drawn(piv.sparkSession, piv.count() if n is None else n, pairs, seed)
    return draw.join(piv.toDF("u", "pu"), "u").join(piv.toDF("w", "pv"), "w").select("pu", "pv")


def pivot_quality(piv: DataFrame, pairs: int | None = None, seed: int = 42, n: int | None = None) -> DataFrame:
    """quality (sum over ordered pairs of the best bound), n_pairs, and the standard error of the mean if sampled.

    ``pairs``: how many pairs are drawn, of n vertices (see ``drawn_pairs``); None counts all, for small networks only."""
    if pairs is None:
        a, b = piv.toDF("u", "pu"), piv.toDF("v", "pv")
        bound = a.crossJoin(b).where("u <> v").select(lb_dist(F.col("pu"), F.col("pv")).alias("x"))
    else:
        bound = drawn_pairs(piv, pairs, seed, n).select(lb_dist(F.col("pu"), F.col("pv")).alias("x"))
    return bound.agg(F.sum("x").alias("quality"), F.count(F.lit(1)).alias("n_pairs"), (F.stddev("x") / F.sqrt(F.count(F.lit(1)))).alias("mean_error"))


def pivot_quality_by_d(piv: DataFrame) -> DataFrame:
    """d, quality, n_pairs of the first d pivots, for every d, over all ordered pairs in one pass.

    A pair's bound is the same both ways, so each is looked at once; the bounds of all d are running maxima of one row of gaps."""
    n = len(piv.first()["piv"])
    at = lambda x: piv.select(F.col("v").alias(x), *[F.get("piv", F.lit(i)).alias(f"{x}{i}") for i in range(n)])
    gaps = [F.abs(F.col(f"a{i}") - F.col(f"b{i}")) for i in range(n)]
    best = [gaps[0], *(F.greatest(*gaps[: i + 1]) for i in range(1, n))]
    sums = at("a").crossJoin(at("b")).where("a < b").agg(*[F.sum(x).alias(f"s{i}") for i, x in enumerate(best)], F.count(F.lit(1)).alias("n"))
    rows = F.explode(F.array(*[F.struct(F.lit(i + 1).alias("d"), (2 * F.col(f"s{i}")).alias("quality"), (2 * F.col("n")).alias("n_pairs")) for i in range(n)]))
    return sums.select(rows.alias("x")).select("x.d", "x.quality", "x.n_pairs")


class Choice(NamedTuple):
    """pivots; trace: quality after the first set and each accepted swap of the best restart; quality of the pivots over
    all ordered pairs, and its standard error where pairs are drawn (else 0)."""

    pivots: list[int]
    trace: list[float]
    quality: float
    error: float


class Scorer:
    """Quality of sets of candidates (by place in ``candidates``), estimated over all n (n - 1) ordered pairs.

    ``pairs``: pairs are drawn from all vertices, and what reaches the driver is pairs x candidates differences; None counts every
    pair in a job for each set, for small networks. Sets are ranked on one draw; ``measure`` takes another, so that the
    quality stated isn't that of the pairs which the set was chosen on."""

    def __init__(self, net: Network, candidates: list[int], pairs: int | None, seed: int) -> None:
        self.candidates, self.pairs, self.seed = candidates, pairs, seed
        self.n = net.vertices.count()
        # of drawn pairs, here and in ``measure``, only the ends' distances are asked for
        spark, ends = net.vertices.sparkSession, None
        if pairs is not None:
            both = drawn(spark, self.n, pairs, seed).unionAll(drawn(spark, self.n, pairs, seed + 1))
            ends = both.select(F.explode(F.array("u", "w")).alias("v")).distinct()
        self.piv = pivot_distances(net, candidates, ends)
        if pairs is not None:
            gaps = drawn_pairs(self.piv, pairs, seed, self.n).select(F.zip_with("pu", "pv", lambda a, b: F.abs(a - b)).alias("gap")).collect()
            self.gaps = np.array([r[0] for r in gaps], np.int64).reshape(len(gaps), len(candidates))

    def columns(self, chosen: list[int]) -> DataFrame:
        return self.piv.select("v", F.array(*[F.get("piv", F.lit(c)) for c in chosen]).alias("piv"))

    def __call__(self, chosen: list[int]) -> float:
        if self.pairs is None:
            return float(pivot_quality(self.columns(chosen)).first()["quality"] or 0)
        return float(self.gaps[:, chosen].max(axis=1).mean() * self.n * (self.n - 1)) if len(self.gaps) else 0.0

    def measure(self, chosen: list[int]) -> tuple[float, float]:
        if self.pairs is None:
            return self(chosen), 0.0
        r = pivot_quality(self.columns(chosen), self.pairs, self.seed + 1, self.n).first()
        whole = self.n * (self.n - 1)
        return (r["quality"] or 0) / max(1, r["n_pairs"]) * whole, (r["mean_error"] or 0.0) * whole


def climb(score: Scorer, order: list[int], d: int, rng: random.Random) -> tuple[list[int], list[float]]:
    """The first d of ``order`` improved by the others: each takes the place of a random pivot if the quality rises."""
    chosen = order[:d]
    trace = [score(chosen)]
    for c in order[d:]:
        trial = [*chosen]
        trial[rng.randrange(d)] = c
        if (new := score(trial)) > trace[-1]:
            chosen = trial
            trace.append(new)
    return chosen, trace


def choose_pivots(net: Network, d: int = 5, restarts: int = 3, swaps: int = 20, seed: int = 42, pairs: int | None = 4_000) -> Choice:
    """The best of several random sets, each improved by random swaps with vertices outside it.

    Sets and swaps draw from all vertices of the network, a restart never the same vertex twice, so what is drawn doesn't hang on what is
    kept and the distances of all restarts are found together."""
    rng = random.Random(seed)
    n = net.vertices.count()
    orders = [rng.sample(range(n), min(n, d + swaps)) for _ in range(restarts)]
    candidates = sorted(set().union(*orders))
    place = {v: i for i, v in enumerate(candidates)}
    score = Scorer(net, candidates, pairs, seed)
    climbs = [climb(score, [place[v] for v in order], min(d, n), rng) for order in orders]
    chosen, trace = max(climbs, key=lambda x: x[1][-1])
    return Choice(sorted(candidates[c] for c in chosen), trace, *score.measure(chosen))


def choose_pivot_count(net: Network, most: int = 15, min_gain: float = 0.01, restarts: int = 3, swaps: int = 20, seed: int = 42, pairs: int | None = 4_000) -> tuple[int, list[float]]:
    """The number of pivots after which one more adds less than ``min_gain`` of the quality, and the quality of each number tried.

    Each number has a choice of its own; all share their draws, so their distances are found together."""
    rng = random.Random(seed)
    n = net.vertices.count()
    orders = [rng.sample(range(n), min(n, most + swaps)) for _ in range(restarts)]
    candidates = sorted(set().union(*orders))
    place = {v: i for i, v in enumerate(candidates)}
    score = Scorer(net, candidates, pairs, seed)
    trace: list[float] = []
    for d in range(1, min(most, n) + 1):
        best = max(climb(score, [place[v] for v in order[: d + swaps]], d, rng)[1][-1] for order in orders)
        trace.append(best)
        if d > 1 and best < trace[-2] * (1 + min_gain):
            return d - 1, trace
    return len(trace), trace


def landmarks_behind(queries: DataFrame, net: Network, landmarks: list[int]) -> DataFrame:
    """qid, landmark, turn, behind, place: which landmarks lie behind a query's own destination, as seen from its source.

    ``turn``: cosine between the way from source to destination and on to the landmark; behind: it is positive; place: 1 is the
    straightest, ties to the smaller landmark. Where two of the three points are one, the turn is 0."""
    at = net.vertices.select("v", F.col("x_mm").cast("double").alias("x"), F.col("y_mm").cast("double").alias("y"))
    marked = queries.select("qid", "src", "dst", F.explode(F.lit([int(x) for x in landmarks]).cast("array<bigint>")).alias("landmark"))
    ax, ay, bx, by = (F.col(x) - F.col(y) for x, y in (("tx", "sx"), ("ty", "sy"), ("lx", "tx"), ("ly", "ty")))
    both = F.sqrt(ax * ax + ay * ay) * F.sqrt(bx * bx + by * by)
    turned = marked
    for end, x in (("src", "s"), ("dst", "t"), ("landmark", "l")):
        turned = turned.join(at.toDF(end, f"{x}x", f"{x}y"), end)
    turned = turned.withColumn("turn", F.when(both == 0, 0.0).otherwise((ax * bx + ay * by) / both))
    order = Window.partitionBy("qid").orderBy(F.desc("turn"), "landmark")
    return turned.select("qid", "landmark", "turn", (F.col("turn") > 0).alias("behind"), F.row_number().over(order).alias("place"))


def choose_landmarks(net: Network, d: int = 5, strategy: str = "farthest", seed: int = 42, tries: int = 60, pairs: int | None = 4_000) -> list[int]:
    """'farthest': each next is farthest from those chosen; 'greedy': each next adds most quality among ``tries`` + d vertices drawn
    from the network; 'swap': the climb. A query's own landmarks: ``landmarks_behind``."""
    if strategy == "swap":
        return choose_pivots(net, d, seed=seed).pivots
    if strategy == "greedy":
        rng = random.Random(seed)
        n = net.vertices.count()
        candidates = sorted(rng.sample(range(n), min(n, tries + d)))
        score = Scorer(net, candidates, pairs, seed)
        chosen: list[int] = []
        while len(chosen) < min(d, len(candidates)):
            chosen.append(-max((score([*chosen, c]), -c) for c in range(len(candidates)) if c not in chosen)[1])
        return sorted(candidates[c] for c in chosen)
    spark = net.vertices.sparkSession
    chosen, least = [], None
    at = net.vertices.agg(F.min("v")).first()[0]
    for _ in range(d):
        dist = distances(net.arcs, spark.createDataFrame([(at,)], "src long"), vertices=net.vertices).select("v", "dist")
        if chosen:
            least = least.join(dist, "v").select("v", F.least("least", "dist").alias("least"))
        else:
            least = dist.withColumnRenamed("dist", "least")
        least = stored(least)
        chosen.append(int(at))
        at = least.agg(F.max_by("v", F.struct("least", -F.col("v")))).first()[0]
    return chosen

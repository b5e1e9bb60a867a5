"""Weather on an edge from forecasts at its ends: interpolation, possible worlds, bounds, trips.

Forecasts are right with their confidence, independently. World A: both right, the value is interpolated;
B: only the head's, C: only the tail's; D: neither, the value is unknown. Confidences are integer
percent, so probabilities are integers in ten-thousandths and comparisons are exact. A missing forecast has
confidence 0. Everything is a Column expression and stays in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SLOTS, SLOT_MIN = 24, 60


def idw(wj: Column, wk: Column, f: Column) -> Column:
    """The value at fraction f of the way, weighted by the distance to the other end."""
    return (1 - f) * wj + f * wk


def world_weights(pj: Column, pk: Column) -> tuple[Column, Column, Column, Column]:
    """Probabilities of A, B, C, D in ten-thousandths."""
    return pj * pk, (100 - pj) * pk, pj * (100 - pk), (100 - pj) * (100 - pk)


def worlds(wj: Column, pj: Column, wk: Column, pk: Column, f: Column) -> Column:
    """array of (world, value, prob in ten-thousandths)."""
    a, b, c, d = world_weights(pj, pk)
    unknown = F.lit(None).cast("double")
    rows = (("A", idw(wj, wk, f), a), ("B", wk, b), ("C", wj, c), ("D", unknown, d))
    return F.array(*[F.struct(F.lit(n).alias("world"), v.alias("value"), p.cast("long").alias("prob")) for n, v, p in rows])


def _weight(condition: Column, weight: Column) -> Column:
    return F.when(F.coalesce(condition, F.lit(False)), weight).otherwise(0)


def p_exceeds(wj: Column, pj: Column, wk: Column, pk: Column, f: Column, eps: Column, unknown: float = 0.0) -> Column:
    """P(value > eps) at fraction f, in ten-thousandths; ``unknown`` is the share of world D."""
    a, b, c, d = world_weights(pj, pk)
    known = _weight(idw(wj, wk, f) > eps, a) + _weight(wk > eps, b) + _weight(wj > eps, c)
    return known if unknown == 0 else known + d * F.lit(unknown)


def ub_case(wj: Column, wk: Column, eps: Column) -> Column:
    """1: both ends within eps; 2.1: only the tail; 2.2: only the head; 3: neither."""
    j, k = F.coalesce(wj <= eps, F.lit(True)), F.coalesce(wk <= eps, F.lit(True))
    return F.when(j & k, "1").when(j, "2.1").when(k, "2.2").otherwise("3")


def ub_prob_ok(wj: Column, pj: Column, wk: Column, pk: Column, eps: Column) -> Column:
    """Upper bound of P(value <= eps) over all points of the edge, in ten-thousandths."""
    case = ub_case(wj, wk, eps)
    mixed_head, mixed_tail = 10000 - pk * (100 - pj), 10000 - pj * (100 - pk)
    return F.when(case == "1", 10000).when(case == "2.1", mixed_head).when(case == "2.2", mixed_tail).otherwise((100 - pj) * (100 - pk)).cast("long")


def discarded(ub: Column, alpha_pct: Column) -> Column:
    """The bound rules every point's obstacle in: P(value <= eps) < 1 - alpha everywhere."""
    return ub < 100 * (100 - alpha_pct)


def trip_blocked(tail_w: Column, tail_p: Column, head_w: Column, head_p: Column, t0: Column, w: Column, eps: Column, alpha_pct: Column, unknown: float = 0.0) -> Column:
    """Whether a trip that leaves the tail at minute t0 and takes w meets an obstacle at any point.

    Ends' forecasts are arrays of 24 slots. Within a slot world A's value is linear in time, so its largest
    is at an end of the piece; both ends of every piece are tested."""

    def at(t: Column, wj: Column, pj: Column, wk: Column, pk: Column) -> Column:
        a, b, c, d = world_weights(pj, pk)
        inside = (w - (t - t0)) * wj + (t - t0) * wk > eps * w
        p = _weight(inside, a) + _weight(wk > eps, b) + _weight(wj > eps, c)
        return (p if unknown == 0 else p + d * F.lit(unknown)) >= 100 * alpha_pct

    def piece(s: Column) -> Column:
        i = (s % SLOTS).cast("int")
        wj, pj, wk, pk = F.get(tail_w, i), F.get(tail_p, i), F.get(head_w, i), F.get(head_p, i)
        first, last = F.greatest(t0, s * SLOT_MIN), F.least(t0 + w, (s + 1) * SLOT_MIN)
        return at(first, wj, pj, wk, pk) | at(last, wj, pj, wk, pk)

    return F.exists(F.sequence(F.floor(t0 / SLOT_MIN), F.floor((t0 + w) / SLOT_MIN)), piece)


def trip_safe(kw: Column, s: Column, blocked: Column) -> Column:
    """Whether an edge can be taken: no keyword of the query, and no obstacle on the trip."""
    return ~(F.coalesce(F.arrays_overlap(kw, s), F.lit(False)) | blocked)


def weather_predicates(ends: list[tuple], t0: Column, w: Column, limits: list[tuple], unknown: float = 0.0) -> Column:
    """Whether a trip keeps several limits at once, of one or several types.

    ``ends``: (tail values, tail confidences, head values, head confidences) of each limit's type; ``limits``: (eps,
    alpha_pct, above): above True keeps the value at or below eps, False keeps it at or above (values and limit are negated)."""
    kept = F.lit(True)
    for (tw, tp, hw, hp), (eps, alpha, above) in zip(ends, limits, strict=True):
        if not above:
            tw, hw, eps = F.transform(tw, lambda x: -x), F.transform(hw, lambda x: -x), -eps
        kept = kept & ~trip_blocked(tw, tp, hw, hp, t0, w, eps, alpha, unknown)
    return kept


def py_trip_blocked(tail: tuple, head: tuple, t0: int, w: int, eps: float, alpha_pct: int, unknown: float = 0.0) -> bool:
    """``trip_blocked`` for the in-task search; tail and head: (values, confidences) of 24 slots."""
    need = 100 * alpha_pct
    for s in range(t0 // SLOT_MIN, (t0 + w) // SLOT_MIN + 1):
        i = s % SLOTS
        wj, pj, wk, pk = tail[0][i], tail[1][i], head[0][i], head[1][i]
        bad_j, bad_k = wj > eps, wk > eps
        p = (pj * (100 - pk) if bad_j else 0) + ((100 - pj) * pk if bad_k else 0) + (100 - pj) * (100 - pk) * unknown
        if p >= need:
            return True
        if (bad_j or bad_k) and p + pj * pk >= need:
            for t in (max(t0, s * SLOT_MIN), min(t0 + w, (s + 1) * SLOT_MIN)):
                if (w - (t - t0)) * wj + (t - t0) * wk > eps * w:
                    return True
    return False

"""Declared schemas and parameters; nothing is inferred from data.

Units: minutes, milli-miles, integer percent; weather values are doubles."""

from __future__ import annotations

from dataclasses import dataclass, field

VERTICES = "net string, v long, x_mm long, y_mm long, cell int"
EDGES = "net string, eid long, a long, b long, len_mm long, w_min long, kw array<int>"
FORECASTS = "cell int, wtype string, slot int, value double, conf_pct int, issued timestamp"
QUERIES = "qid int, src long, dst long, dep_min long, wtype string, eps double, alpha_pct int, s array<int>"
ANSWERS = "qid int, answered boolean, total_min long, hops int, vertices array<long>, edges array<long>, arr array<long>"
PROPS = "k int"
SLOTS, SLOT_MIN = 24, 60
#: Side of the square box of all networks and of a station's cell.
BOX_MM, CELL_MM = 400_000, 80_000


@dataclass(frozen=True)
class RouteOptions:
    """Switches of every routing method.

    path_mode: 'walk' (vertices may repeat; labels are one per vertex and minute) or 'simple'.
    unknown_world: share of the world with both forecasts wrong that counts as exceeding:
    'optimistic' 0, 'pessimistic' 1, or a number.
    horizon_min: labels later than this after departure are dropped.
    key: 'elapsed' or 'elapsed_plus_lb', what the search takes next.
    heuristic: 'zero', 'euclid' or 'pivot', the bound in the key and in time pruning.
    prefilter: for filter-first: 'all_slots', 'departure_slot' or 'any_slot'.
    reverse: bound the rest of the way in tasks by a search back from dst over the arcs that are not blocked
    throughout; the index-guided router has it on.
    label_limit: most labels of one query in a task; a search that has more open raises."""

    path_mode: str = "walk"
    unknown_world: str | float = "optimistic"
    horizon_min: int = 360
    key: str = "elapsed_plus_lb"
    heuristic: str = "pivot"
    use_index: bool = True
    use_keyword: bool = True
    use_weather: bool = True
    use_time: bool = True
    prefilter: str = "all_slots"
    batch_width: int | None = None
    reverse: bool = False
    label_limit: int | None = None
    extra: dict = field(default_factory=dict)

    @property
    def unknown(self) -> float:
        return {"optimistic": 0.0, "pessimistic": 1.0}.get(self.unknown_world, self.unknown_world)

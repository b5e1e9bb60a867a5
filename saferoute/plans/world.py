"""What several queries share: networks, forecasts, pivots, indexes and query sets, built once per session and folder."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor, wait
from threading import Lock, RLock

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.pivots import choose_landmarks, fixed_pivots, pivot_distances
from ..operators.storage import hand_back, stored
from ..sources import forecasts, networks
from ..sources.queries import make_queries, query_ends
from .index import Index, build_index

FANOUT = 48


#: Seconds after which the driver's heap is handed back while calls run side by side.
HAND_BACK_S = 4
_handing = Lock()


def together(spark: SparkSession, *makes: Callable, at_once: int | None = None) -> list:
    """Results of calls that are made all at once (or ``at_once`` of them), each in a thread; the first error is raised."""
    mine = _handing.acquire(blocking=False)  # one hands back for all that run
    try:
        with ThreadPoolExecutor(at_once or len(makes)) as pool:
            made = [pool.submit(inheritable_thread_target(spark)(m)) for m in makes]
            while mine and wait(made, HAND_BACK_S).not_done:
                hand_back(spark)
            return [f.result() for f in made]
    finally:
        if mine:
            _handing.release()


class World:
    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        self.spark, self.sf_dir = spark, sf_dir
        self._kept: dict = {}
        self._locks: dict = {}
        self._lock = Lock()

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")

    def _once(self, key: tuple, make):  # noqa: ANN001, ANN202
        """What ``make`` gives, made once; other threads that ask for the same wait for it."""
        with self._lock:
            own = self._locks.setdefault(key, RLock())
        with own:
            if key not in self._kept:
                self._kept[key] = make()
        return self._kept[key]

    def net(self, kind: str = "uni") -> networks.Network:
        """'uni', 'gau' or 'sparse'; 'uni/2': of two quarters of the vertices; 'uni+8': a cross link at every eighth; 'uni*': skewed keywords."""

        def make() -> networks.Network:
            name, quarters, period = kind.rstrip("*"), 4, None
            if "+" in name:
                name, period = name.split("+")[0], int(name.split("+")[1])
            if "/" in name:
                name, quarters = name.split("/")[0], int(name.split("/")[1])
            # networks of several periods share their vertices, and those of several keywords their roads
            vertices = self._once(("vertices", name, quarters), lambda: networks.build_vertices(self.spark, self.sf_dir, name, quarters))
            roads = self._once(("roads", name, quarters, period), lambda: networks.build_roads(vertices, name, period))
            return networks.build_network(self.spark, self.sf_dir, name, quarters, period, kind.endswith("*"), vertices, roads)

        return self._once(("net", kind), make)

    @property
    def ring(self) -> DataFrame:
        return self._once(("ring",), lambda: stored(forecasts.ring(self.table("events"))))

    def piv(self, kind: str = "uni", d: int = 5, strategy: str = "fixed") -> DataFrame:
        """'fixed': evenly spread, as SQL can say them; else a strategy of ``choose_landmarks``. Keywords don't matter."""
        kind = kind.rstrip("*")

        def make() -> DataFrame:
            net = self.net(kind)
            return pivot_distances(net, fixed_pivots(net, d) if strategy == "fixed" else choose_landmarks(net, d, strategy))

        return self._once(("piv", kind, d, strategy), make)

    def pivs(self, kind: str, numbers: tuple) -> None:
        """``piv`` of several numbers of fixed pivots, whose distances are found together."""
        sets = {d: fixed_pivots(self.net(kind), d) for d in numbers}
        every = sorted(set().union(*sets.values()))
        whole = self._once(("pivs", kind, numbers), lambda: pivot_distances(self.net(kind), every))
        for d, own in sets.items():
            part = whole.select("v", F.array(*[F.get("piv", F.lit(every.index(p))) for p in own]).alias("piv")).where(F.array_max("piv") >= 0)
            self._once(("piv", kind, d, "fixed"), lambda part=part: stored(part))

    def index(self, kind: str = "uni", fanout: int = FANOUT, d: int = 5, wtypes: tuple = ("ANY",), strategy: str = "fixed") -> Index:
        """Indexes of several pivots share all else, and those of several keywords the weather of their nodes."""

        def base(kind: str) -> Index:
            own, plain = build_index(self.net(kind), self.ring, fanout, wtypes=wtypes), kind.rstrip("*")
            return own if kind == plain else own.sharing(self._once(("index", plain, fanout, wtypes), lambda: base(plain)), ("weather", "links", "by_slot", "vmax"))

        shared = self._once(("index", kind, fanout, wtypes), lambda: base(kind))

        def make() -> Index:
            own, plain = shared.with_pivots(self.net(kind), lambda: self.piv(kind, d, strategy)), kind.rstrip("*")
            return own if kind == plain else own.sharing(self.index(plain, fanout, d, wtypes, strategy), ("ranges",))

        return self._once(("index", kind, fanout, d, wtypes, strategy), make)

    def ready(self, kind: str = "uni", d: int = 5, strategy: str = "fixed", n: int = 20, sigma: int = 10, **options) -> None:
        """Makes what the index method needs on a network; parts that don't need each other are made side by side, as few of their jobs fill all cores."""
        together(self.spark, lambda: self.net(kind), lambda: self.ring)
        plain = kind.rstrip("*")
        if kind != plain:
            self.net(plain)
        together(self.spark, lambda: self.piv(plain, d, strategy), lambda: self.queries(kind, n, sigma, **options), lambda: self.index(plain, d=d, strategy=strategy).by_slot)
        index = self.index(kind, d=d, strategy=strategy)
        together(self.spark, lambda: index.ranges, lambda: index.pages, lambda: index.nodes)

    def queries(self, kind: str = "uni", n: int = 20, sigma: int = 10, **options) -> DataFrame:
        ends = self._once(("ends", kind.rstrip("*"), n, sigma), lambda: query_ends(self.net(kind), n, sigma))
        return self._once(("queries", kind, n, sigma, *sorted(options.items())), lambda: make_queries(self.net(kind), n, sigma, **options, ends=ends))


_worlds: dict[tuple, World] = {}


def world(spark: SparkSession, sf_dir: str) -> World:
    key = spark.sparkContext.applicationId, sf_dir
    if key not in _worlds:
        _worlds.clear()
        _worlds[key] = World(spark, sf_dir)
    return _worlds[key]

"""All-k-nearest-neighbour search and classification, by the growing-ball method and by its baselines."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.vote import majority
from ..operators import brute, merge, probe
from ..operators.density import cell_counts, with_walls
from ..operators.grid import GridSpec, bounds, suggest
from ..operators.local import PHYSICAL, chunks, lists, train_blocks, unify
from ..operators.points import at_places, places
from ..sources.shared import stored

STRATEGIES = ("grow", "merge", "brute")
GROWTHS = ("certify", "touch", "contain", "points")
#: Rounds after which the literal point-by-point growth is finished by the certified one.
MAX_ROUNDS = 12


@dataclass
class Run:
    """The stages of one search, for the measures."""

    own: DataFrame | None = None
    balls: DataFrame | None = None
    probes: DataFrame | None = None
    updates: DataFrame | None = None
    counts: DataFrame | None = None
    train: DataFrame | None = None
    query: DataFrame | None = None
    regions: DataFrame | None = None
    extra: list[DataFrame] = field(default_factory=list)
    final: DataFrame | None = None
    k: int = 0


@dataclass
class Prepared:
    """A training set whose cells are counted and whose points lie in blocks: made once, searched often."""

    grid: GridSpec
    train: DataFrame
    counts: DataFrame
    blocks: DataFrame
    split: bool


def prepare(train: DataFrame, grid: GridSpec, tight: bool = True) -> Prepared:
    """What a search needs of its training points (tid, t0.., cls), stored."""
    placed = grid.assign(train, "t")
    counts = cell_counts(placed, grid)
    counts = stored(counts if tight else with_walls(counts, grid), "cell-counts")
    return Prepared(grid, placed, counts, train_blocks(placed, grid.d, counts), chunks(counts) > 1)


def fitted_grid(query: DataFrame, train: DataFrame, per_cell: float = 32.0) -> GridSpec:
    """A power-of-two grid over the box of both tables, of about per_cell training points a cell."""
    d = _axes(query, "q")
    lo, hi = bounds(train, query, d)
    return suggest(train.count(), d, per_cell, lo, hi) or GridSpec.pow2(d, 1, lo, hi)


def _check(d: int, k: int, grid: GridSpec | None, strategy: str, growth: str | None, physical: str) -> None:
    if k < 1:
        raise ValueError("k is at least 1")
    if strategy not in STRATEGIES or physical not in PHYSICAL or growth not in (None, *GROWTHS):
        raise ValueError("unknown strategy, growth or physical form")
    if strategy != "brute" and (grid is None or grid.d != d):
        raise ValueError("the grid needs an axis for each coordinate")
    if strategy == "merge" and growth is not None:
        raise ValueError("merging leaves nothing to grow")
    if strategy == "merge" and not grid.is_pow2:
        raise ValueError("merging needs a power-of-two grid with equal slices")


def _axes(df: DataFrame, prefix: str) -> int:
    return sum(c.startswith(prefix) and c[1:].isdigit() for c in df.columns)


def _kth(nn: Column, k: int) -> Column:
    return F.try_element_at(nn, F.lit(k))["dist"]


def search(query: DataFrame, train: DataFrame | Prepared, k: int, grid: GridSpec | None = None, metric: str = "euclidean", strategy: str = "grow", growth: str | None = None, step: str = "half_cell", physical: str = "arrow", exclude_self: bool = False, growth_scope: str = "point", tight: bool | None = None) -> Run:
    """pid and nn (the list) for each query as Run.final, with the stages that led there.

    train: training points, or what prepare() made of them (then with its grid). Stages are
    stored as they are reached, because later ones read them more than once; only the last one
    is a plan that hasn't run. tight: overlap is tested against the tight boxes of the cells'
    points instead of the cells' walls; the default, except for the literal reading `touch`.
    Rows with a null coordinate or id belong in points.validate() first; `merge` leaves them out.
    """
    d = _axes(query, "q")
    ready = train if isinstance(train, Prepared) else None
    grid = ready.grid if ready else grid
    _check(d, k, grid, strategy, growth, physical)
    if strategy == "brute":
        return Run(train=train, query=query, k=k, final=brute.all_knn(query, train, d, k, metric, physical, exclude_self))
    tight = growth != "touch" if tight is None else tight
    query = grid.assign(query, "q")
    if strategy == "merge":
        placed = ready.train if ready else grid.assign(train, "t")
        counts = ready.counts if ready else stored(cell_counts(placed, grid) if tight else with_walls(cell_counts(placed, grid), grid), "cell-counts")
        run = Run(train=placed, query=query, counts=counts, k=k)
        run.regions = stored(merge.regions(placed, query, grid, k), "regions")
        query, united = merge.relabel(query, run.regions), merge.relabel(placed, run.regions)
        held = stored(united.groupBy("cell").agg(F.count("*").alias("n")), "region-counts")
        blocks, split = train_blocks(united, d, held), chunks(held) > 1
        growth = "contain"
    else:
        ready = ready or prepare(train, grid, tight)
        run = Run(train=ready.train, query=query, counts=ready.counts, k=k)
        blocks, split = ready.blocks, ready.split
    # a query point must not count as its own neighbour, so one more may be needed
    wanted = k + 1 if exclude_self else k
    coords = [f"q{i}" for i in range(d)]
    first = lists(query, blocks, d, k, metric, physical, exclude_self=exclude_self, keep_empty=True)
    own = unify(first, k, [*coords, "cell"]) if split else first
    # length and last distance of a list lie beside it, so that plans which need only those don't read the list
    run.own = own = stored(own.withColumn("held", F.size("nn")).withColumn("r", _kth(F.col("nn"), k)), "own-lists")
    full = own.filter(F.col("held") >= k).withColumn("growths", F.lit(0).cast("long"))
    short = own.filter(F.col("held") < k).drop("r")
    grown = _grow(short, run, grid, k, wanted, metric, growth or "certify", step, growth_scope, blocks, physical, exclude_self)
    # a complete list can only be improved inside its ball; a short one takes all points of the touched cells
    whole = (growth or "certify") in ("touch", "certify") and growth_scope == "point"
    # those of complete lists are read off the lists; only grown ones are stored
    grown = stored(grown.withColumn("limit", F.lit(float("inf")) if whole else F.col("r")), "balls")
    balls = full.withColumn("limit", F.col("r")).unionByName(grown)
    # regions have no walls of their own, so merging has no fast exit
    done = F.lit(False) if strategy == "merge" else (F.col("growths") == 0) & (F.col("held") >= k) & _inside_own_cell(grid)
    run.balls = balls = balls.withColumn("done", done)
    open_ = balls.filter("not done")
    run.probes = stored(_other_cells(open_.select("pid", *coords, "cell", "r", "limit", (F.col("held") < k).alias("short")), run, grid, metric), "probes")
    found = lambda probes: lists(probes.withColumn("r", F.col("limit")), blocks, d, k, metric, physical, within=True, exclude_self=exclude_self).select("pid", "nn")
    run.updates = own.select("pid", "nn").unionByName(found(run.probes))
    if (growth or "certify") in ("certify", "points"):
        # only short lists are looked at once more, so the others needn't be made before they are asked for
        short, rest = open_.filter(F.col("held") < k), open_.filter(F.col("held") >= k)
        touched = stored(unify(short.select("pid", "nn").unionByName(found(run.probes.filter("short"))), k, []), "touched-lists")
        touched = _certified(touched, balls.filter(F.col("held") < k), run, grid, k, metric, blocks, physical, exclude_self)
        touched = touched.unionByName(unify(rest.select("pid", "nn").unionByName(found(run.probes.filter("not short"))), k, []))
    else:
        touched = unify(open_.select("pid", "nn").unionByName(found(run.probes)), k, [])
    run.final = balls.filter("done").select("pid", "nn").unionByName(touched)
    return run


def _inside_own_cell(grid: GridSpec) -> Column:
    """Whether the ball (q0.., r) lies inside the walls of the query's own cell; border cells have no outer walls.

    Points of other cells then differ by more than r on some axis, whatever the metric.
    """
    inside = F.lit(True)
    for i in range(grid.d):
        x, index = F.col(f"q{i}"), grid.index(i, F.col(f"q{i}"))
        reach = F.col("r") * (1 + 1e-9) + 1e-12
        inside = inside & (grid.index(i, x - reach) == index) & (grid.index(i, x + reach) == index)
    return inside


def _grow(short: DataFrame, run: Run, grid: GridSpec, k: int, wanted: int, metric: str, growth: str, step: str, scope: str, blocks: DataFrame, physical: str, exclude_self: bool) -> DataFrame:
    """short with its ball's r and how often it grew."""
    d = grid.d
    far = probe.safe_radius(short, run.counts, grid, wanted, metric)
    if scope == "cell":
        return far.withColumn("r", F.col("far")).withColumn("growths", F.lit(1).cast("long")).drop("far")
    start = F.when(F.size("nn") > 0, F.try_element_at("nn", F.lit(-1))["dist"]).otherwise(grid.width() / 2)
    if growth == "points":
        return _grow_by_points(far, start, run, grid, k, metric, blocks, physical, exclude_self)
    reached = probe.reach(stored(far, "safe-radius"), run.counts, grid, wanted, metric, contain=growth == "contain")
    if growth == "contain":
        return reached.withColumn("r", F.greatest(F.col("need"), start)).withColumn("growths", F.lit(1).cast("long")).drop("far", "need")
    r, growths = probe.stepped(F.greatest(start, F.lit(1e-300)), F.col("need"), grid, step)
    return reached.withColumn("r", r).withColumn("growths", growths).drop("far", "need")


def _grow_by_points(far: DataFrame, start: Column, run: Run, grid: GridSpec, k: int, metric: str, blocks: DataFrame, physical: str, exclude_self: bool) -> DataFrame:
    """The reading in which the ball doubles until it holds k points themselves; a bounded number of rounds."""
    coords = [f"q{i}" for i in range(grid.d)]
    columns = ["pid", *coords, "cell", "nn", "held", "r", "growths"]
    open_ = stored(far.withColumn("r", F.greatest(start, F.lit(grid.width() / 2))).withColumn("growths", F.lit(0).cast("long")), "points-0")
    done = open_.filter("false").select(columns)
    for i in range(1, MAX_ROUNDS + 1):
        if open_.isEmpty():
            return done
        open_ = open_.withColumn("r", F.least(F.col("r") * 2, F.greatest("far", "r"))).withColumn("growths", F.col("growths") + 1)
        others = _other_cells(open_.select("pid", *coords, "cell", "r"), run, grid, metric)
        seen = open_.select("pid", "nn").unionByName(lists(others, blocks, grid.d, k, metric, physical, within=True, exclude_self=exclude_self).select("pid", "nn"))
        inside = unify(seen, k, []).select("pid", F.size("nn").alias("inside"), F.try_element_at("nn", F.lit(-1))["dist"].alias("last"))
        tested = stored(open_.join(inside, "pid"), f"points-{i}")
        ended = ((F.col("inside") >= k) & (F.col("last") <= F.col("r"))) | (F.col("r") >= F.col("far"))
        done = done.unionByName(tested.filter(ended).select(columns))
        open_ = tested.filter(~ended).drop("inside", "last")
    return done.unionByName(open_.withColumn("r", F.col("far")).select(columns))


def _other_cells(balls: DataFrame, run: Run, grid: GridSpec, metric: str, beyond: str | None = None) -> DataFrame:
    """(pid, q0.., r, cell, n): the touched cells, or regions, other than the query's own."""
    kept = [c for c in balls.columns if c != "cell"]
    hit = probe.overlapped(balls.withColumnRenamed("cell", "own"), run.counts, grid, metric, beyond).select(*kept, "own", "cell", "n")
    if run.regions is not None:
        hit = hit.join(run.regions.select("cell", "region"), "cell").groupBy(*kept, "own", F.col("region").alias("cell")).agg(F.sum("n").alias("n"))
    return hit.filter(F.col("cell") != F.col("own")).drop("own")


def _certified(final: DataFrame, balls: DataFrame, run: Run, grid: GridSpec, k: int, metric: str, blocks: DataFrame, physical: str, exclude_self: bool) -> DataFrame:
    """Lists whose k-th distance passes their ball get one more probe, of the cells in between only.

    balls: those of short lists; a complete list ends where its ball does.
    """
    coords = [f"q{i}" for i in range(grid.d)]
    last = F.when(F.size("nn") >= k, _kth(F.col("nn"), k))
    doubtful = final.join(balls.select("pid", *coords, "cell", F.col("r").alias("searched")), "pid").withColumn("r", last).filter(F.col("r") > F.col("searched"))
    again = stored(_other_cells(doubtful.select("pid", *coords, "cell", "r", "searched"), run, grid, metric, beyond="searched"), "rechecked")
    run.extra.append(again)
    more = lists(again, blocks, grid.d, k, metric, physical, within=True, exclude_self=exclude_self)
    return unify(final.unionByName(more.select("pid", "nn")), k, [])


def shared_places(query: DataFrame, d: int) -> DataFrame | None:
    """places(query), stored, where they are at most half as many as the queries; else None."""
    n, about = query.agg(F.count("*"), F.approx_count_distinct(F.struct(*[f"q{i}" for i in range(d)]))).first()
    # an estimate that can't be that far off: far more places than that aren't grouped and stored only to be counted
    if about > 0.65 * n:
        return None
    seen = stored(places(query, d), "places")
    return seen if 2 * seen.count() <= n else None


def _once_a_place(query: DataFrame, train: DataFrame | Prepared, k: int, grid: GridSpec | None, options: dict) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """pid, nn of the queries, or of the places they share, and what makes rows of queries of the latter's."""
    d = _axes(query, "q")
    seen = None if options.get("exclude_self") else shared_places(query, d)
    if seen is None:
        return search(query, train, k, grid, **options).final, lambda found: found
    return search(seen.drop("copies"), train, k, grid, **options).final, lambda found: at_places(found, seen, query, d)


def all_knn(query: DataFrame, train: DataFrame | Prepared, k: int, grid: GridSpec | None = None, **options) -> DataFrame:
    """Long form: pid, rank, tid, dist, cls. Queries at one place are searched once."""
    nn, for_all = _once_a_place(query, train, k, grid, options)
    nn = for_all(nn)
    return nn.select("pid", F.posexplode("nn").alias("rank", "x")).select("pid", (F.col("rank") + 1).alias("rank"), "x.tid", "x.dist", "x.cls")


def classify(query: DataFrame, train: DataFrame | Prepared, k: int, grid: GridSpec | None = None, tie: str = "nearest", weighted: bool = False, keep_neighbours: bool = False, **options) -> DataFrame:
    """pid, cls_pred, votes, best_rank (and nn). The vote is a projection of the unified lists, made once for queries at one place."""
    nn, for_all = _once_a_place(query, train, k, grid, options)
    voted = nn.withColumn("v", majority(F.col("nn"), tie, weighted))
    voted = for_all(voted if keep_neighbours else voted.drop("nn"))
    return voted.select("pid", "v.cls_pred", "v.votes", "v.best_rank", *(["nn"] if keep_neighbours else []))

"""Registered queries of the point methods, and for each the DuckDB statement of the same rows.

Distances leave as floor(dist * 1e6), so that both engines hash the same integers.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import joins, merge, probe, quality
from ..operators.density import cell_counts
from ..operators.grid import GridSpec, bounds
from ..operators.points import fraction, split
from . import cost, pipeline, workloads
from .profiles import DEFAULT_N, PROFILES

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}
MICRO = 1e6


def _micro(c: str = "dist"):
    return F.floor(F.col(c) * F.lit(MICRO)).cast("long").alias(f"{c}6")


def _grid(name: str) -> GridSpec:
    return GridSpec.pow2(PROFILES[name].d, DEFAULT_N[name])


# ---- statements -------------------------------------------------------------------------


def _points(name: str, more: str = "") -> str:
    return f"WITH p AS ({PROFILES[name].sql()}), q AS (SELECT * FROM p WHERE pid % 10 <> 0 {more}), t AS (SELECT pid AS tid, * EXCLUDE (pid) FROM p WHERE pid % 10 = 0 {more})"


def _dist(d: int, metric: str = "euclidean", a: str = "q", b: str = "t") -> str:
    parts = [f"({a}.x{i} - {b}.x{i})" for i in range(d)]
    if metric == "manhattan":
        return " + ".join(f"abs{x}" for x in parts)
    if metric == "chebyshev":
        return "greatest(" + ", ".join(f"abs{x}" for x in parts) + ")"
    return "sqrt(" + " + ".join(f"{x} * {x}" for x in parts) + ")"


def _cell(d: int, n: int, a: str) -> str:
    """Indices of a power-of-two grid of the unit box, as a tuple of columns."""
    m = 1 << n
    return ", ".join(f"least(greatest(floor(({a}x{i} - 0.0::double) * {m} / 1.0::double), 0), {m - 1})::int AS c{i}" for i in range(d))


def _same_cell(d: int, a: str, b: str) -> str:
    return " AND ".join(f"{a}.c{i} = {b}.c{i}" for i in range(d))


def _ranked(name: str, k: int, metric: str = "euclidean", where: str = "TRUE", more: str = "") -> str:
    d = PROFILES[name].d
    return f"{_points(name, more)}, pairs AS (SELECT q.pid, t.tid, t.cls, {_dist(d, metric)} AS dist FROM q, t WHERE {where}), nn AS (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY dist, tid) AS rank FROM pairs QUALIFY rank <= {k})"


def _lists_sql(*args, **kw) -> str:
    return _ranked(*args, **kw) + " SELECT pid, rank::int AS rank, tid, floor(dist * 1e6)::bigint AS dist6 FROM nn"


def _vote_sql(ranked: str) -> str:
    return ranked + ", votes AS (SELECT pid, cls, count(*) AS votes, min(rank) AS best FROM nn GROUP BY pid, cls), pred AS (SELECT pid, cls AS cls_pred, votes, best AS best_rank FROM votes QUALIFY row_number() OVER (PARTITION BY pid ORDER BY votes DESC, best) = 1)"


# ---- registration -----------------------------------------------------------------------


def _add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLE[name] = sql


def _sides(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    return PROFILES[name].split(spark, sf_dir)


def _knn_query(name: str, k: int, **options) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, name)
        grid = GridSpec.quantile(train, [1 << DEFAULT_N[name]] * PROFILES[name].d) if options.get("quantile") else pipeline.fitted_grid(query, train)
        rows = pipeline.all_knn(query, train, k, grid, **{a: b for a, b in options.items() if a != "quantile"})
        return rows.select("pid", F.col("rank").cast("int").alias("rank"), "tid", _micro())

    return run


for _name, _k in (("skew1", 5), ("skew2", 5), ("skew2", 10), ("skew3", 5), ("unif1", 5), ("unif2", 5), ("unif3", 10), ("part2", 10)):
    _add(f"allknn_{_name}_k{_k}", _knn_query(_name, _k), _lists_sql(_name, _k))
for _metric in ("manhattan", "chebyshev"):
    _add(f"allknn_{_metric}_unif2", _knn_query("unif2", 5, metric=_metric), _lists_sql("unif2", 5, _metric))
_add("contain_allknn_unif2", _knn_query("unif2", 5, growth="contain"), _lists_sql("unif2", 5))
_add("points_allknn_skew2", _knn_query("skew2", 5, growth="points"), _lists_sql("skew2", 5))
_add("cell_scope_allknn_skew3", _knn_query("skew3", 5, growth_scope="cell"), _lists_sql("skew3", 5))
_add("quantile_allknn_skew2", _knn_query("skew2", 5, quantile=True), _lists_sql("skew2", 5))
_add("pairs_allknn_unif2", _knn_query("unif2", 5, physical="pairs"), _lists_sql("unif2", 5))
_add("blocked_allknn_skew3", _knn_query("skew3", 5, physical="blocked"), _lists_sql("skew3", 5))
_add("arrow_allknn_skew3", _knn_query("skew3", 5, physical="arrow"), _lists_sql("skew3", 5))
_MINKOWSKI = "pow(pow(abs(q.x0 - t.x0), 3.25::double) + pow(abs(q.x1 - t.x1), 3.25::double), 1 / 3.25::double)"
_add("allknn_minkowski_unif2", _knn_query("unif2", 5, metric="minkowski3.25"), _lists_sql("unif2", 5).replace(_dist(2), _MINKOWSKI))
for _step in ("cell", "double", "continuous"):
    _add(f"step_{_step}_allknn_skew2", _knn_query("skew2", 5, step=_step), _lists_sql("skew2", 5))
_add("merge_allknn_unif2", _knn_query("unif2", 5, strategy="merge"), _lists_sql("unif2", 5))
_add("brute_allknn_unif2", _knn_query("unif2", 5, strategy="brute"), _lists_sql("unif2", 5))
for _d in (4, 6):
    _add(f"allknn_emb{_d}", _knn_query(f"emb_{_d}", 5), _lists_sql(f"emb_{_d}", 5))


def bounds_skew3(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "skew3")
    lo, hi = bounds(train, query, 3)
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(zip(lo, hi, strict=True))], "axis int, lo double, hi double")


_add("bounds_skew3", bounds_skew3, f"WITH p AS ({PROFILES['skew3'].sql()}) " + " UNION ALL ".join(f"SELECT {i}::int AS axis, min(x{i}) AS lo, max(x{i}) AS hi FROM p" for i in range(3)))


def _density(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, _ = _sides(spark, sf_dir, name)
        return cell_counts(train, _grid(name)).select(*[f"idx{i}" for i in range(PROFILES[name].d)], F.col("n").alias("n_train"))

    return run


for _name in ("skew1", "skew2", "skew3", "unif2"):
    _p = PROFILES[_name]
    _add(f"density_{_name}", _density(_name), f"{_points(_name)}, placed AS (SELECT {_cell(_p.d, DEFAULT_N[_name], '')} FROM t) SELECT " + ", ".join(f"c{i} AS idx{i}" for i in range(_p.d)) + ", count(*) AS n_train FROM placed GROUP BY ALL")


def _own_cell_sql(name: str) -> str:
    d, n = PROFILES[name].d, DEFAULT_N[name]
    return f"{_points(name)}, qc AS (SELECT *, {_cell(d, n, '')} FROM q), tc AS (SELECT *, {_cell(d, n, '')} FROM t), own AS (SELECT q.pid, t.tid, {_dist(d)} AS dist FROM qc q JOIN tc t ON {_same_cell(d, 'q', 't')}), nn AS (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY dist, tid) AS rank FROM own QUALIFY rank <= 5)"


def _own_lists(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, name)
    return pipeline.search(query, train, 5, _grid(name)).own


def _own_cell(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: _own_lists(spark, sf_dir, name).select("pid", F.posexplode("nn").alias("r", "x")).select("pid", (F.col("r") + 1).cast("int").alias("rank"), "x.tid", F.col("x.dist").alias("dist")).select("pid", "rank", "tid", _micro())


def _short(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: _own_lists(spark, sf_dir, name).filter(F.size("nn") < 5).select("pid", F.size("nn").cast("long").alias("held"))


def _empty(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, name)
        grid = _grid(name)
        return grid.assign(query, "q").join(cell_counts(train, grid).select("cell"), "cell", "left_anti").select("pid")

    return run


for _name in ("skew2", "unif2"):
    _add(f"own_cell_{_name}", _own_cell(_name), _own_cell_sql(_name) + " SELECT pid, rank::int AS rank, tid, floor(dist * 1e6)::bigint AS dist6 FROM nn")
    _add(f"short_points_{_name}", _short(_name), _own_cell_sql(_name) + " SELECT q.pid, count(nn.tid) AS held FROM q LEFT JOIN nn USING (pid) GROUP BY q.pid HAVING count(nn.tid) < 5")
_add("empty_cell_queries_skew2", _empty("skew2"), _own_cell_sql("skew2") + " SELECT pid FROM q WHERE pid NOT IN (SELECT pid FROM nn)")


def _reach(contain: bool) -> Callable[[SparkSession, str], DataFrame]:
    """The distance at which touched (or contained) tight cell boxes hold k points, for every query."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, "skew2")
        grid = _grid("skew2")
        counts = cell_counts(train, grid)
        far = probe.safe_radius(grid.assign(query, "q"), counts, grid, 5)
        return probe.reach(far, counts, grid, 5, contain=contain).select("pid", _micro("need"))

    return run


def _reach_sql(contain: bool) -> str:
    n = DEFAULT_N["skew2"]
    gap = [f"greatest(lo{i} - q.x{i}, 0.0::double, q.x{i} - hi{i})" for i in range(2)]
    span = [f"greatest(abs(q.x{i} - lo{i}), abs(q.x{i} - hi{i}))" for i in range(2)]
    at = "sqrt(" + " + ".join(f"{x} * {x}" for x in (span if contain else gap)) + ")"
    return f"{_points('skew2')}, tc AS (SELECT *, {_cell(2, n, '')} FROM t), boxes AS (SELECT c0, c1, count(*) AS n, min(x0) AS lo0, max(x0) AS hi0, min(x1) AS lo1, max(x1) AS hi1 FROM tc GROUP BY c0, c1), run AS (SELECT q.pid, {at} AS edge, sum(n) OVER (PARTITION BY q.pid ORDER BY {at} RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS held FROM q, boxes) SELECT pid, floor(min(edge) * 1e6)::bigint AS need6 FROM run WHERE held >= 5 GROUP BY pid"


_add("radius_touch_skew2", _reach(False), _reach_sql(False))
_add("radius_contain_skew2", _reach(True), _reach_sql(True))


def _classify(name: str, k: int, **options) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, name)
        out = pipeline.classify(query, train, k, pipeline.fitted_grid(query, train), **options)
        return out.select("pid", "cls_pred", F.col("votes").cast("long").alias("votes"), F.col("best_rank").cast("long").alias("best_rank"))

    return run


_PRED = " SELECT pid, cls_pred, votes, best_rank FROM pred"
for _name, _k, _o in (("skew3", 10, {}), ("unif3", 10, {}), ("emb_4", 5, {}), ("part2", 4, {})):
    _add(f"classify_{_name}_k{_k}", _classify(_name, _k, **_o), _vote_sql(_ranked(_name, _k)) + _PRED)
_CLASS_TIES = _ranked("part2", 4) + ", votes AS (SELECT pid, cls, count(*) AS votes, min(rank) AS best FROM nn GROUP BY pid, cls), pred AS (SELECT pid, cls AS cls_pred, votes, best AS best_rank FROM votes QUALIFY row_number() OVER (PARTITION BY pid ORDER BY votes DESC, cls) = 1)"
_add("vote_ties_part2", _classify("part2", 4, tie="class"), _CLASS_TIES + _PRED)
_add("classify_merge_unif2", _classify("unif2", 5, strategy="merge"), _vote_sql(_ranked("unif2", 5)) + _PRED)


def _confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "skew3")
    return quality.confusion(pipeline.classify(query, train, 10, pipeline.fitted_grid(query, train)), PROFILES["skew3"].points(spark, sf_dir))


_CONFUSION = _vote_sql(_ranked("skew3", 10)) + ", cells AS (SELECT q.cls AS truth, pred.cls_pred AS pred, count(*) AS n FROM q JOIN pred USING (pid) GROUP BY ALL)"
_RATES = _CONFUSION + ", tot AS (SELECT sum(n) AS total FROM cells), own AS (SELECT truth AS cls, sum(n) AS actual, sum(CASE WHEN truth = pred THEN n ELSE 0 END) AS hit FROM cells GROUP BY truth), said AS (SELECT pred AS cls, sum(n) AS said FROM cells GROUP BY pred), r AS (SELECT cls, hit / actual AS tp, (coalesce(said, 0) - hit) / (total - actual) AS fp FROM own LEFT JOIN said USING (cls), tot)"
_micros = lambda a: [F.round(F.col(c) * F.lit(MICRO)).cast("long").alias(f"{c}6") for c in a]
_add("confusion_skew3", _confusion, _CONFUSION + " SELECT truth, pred, n FROM cells")
_add("rates_skew3", lambda spark, sf_dir: quality.rates(_confusion(spark, sf_dir)).select("cls", *_micros(("tp", "fn", "fp", "tn"))), _RATES + " SELECT cls, round(tp * 1e6)::bigint AS tp6, round((1 - tp) * 1e6)::bigint AS fn6, round(fp * 1e6)::bigint AS fp6, round((1 - fp) * 1e6)::bigint AS tn6 FROM r")
_add("macro_skew3", lambda spark, sf_dir: quality.macro(quality.rates(_confusion(spark, sf_dir))).select(*_micros(("tp", "fn", "fp", "tn"))), _RATES + " SELECT round(avg(tp) * 1e6)::bigint AS tp6, round(avg(1 - tp) * 1e6)::bigint AS fn6, round(avg(fp) * 1e6)::bigint AS fp6, round(avg(1 - fp) * 1e6)::bigint AS tn6 FROM r")


def _pairs(strategy: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, "unif2")
        grid = _grid("unif2")
        q, t = grid.assign(query, "q"), grid.assign(train, "t")
        if strategy == "merge":
            found = merge.regions(t, q, grid, 5)
            q, t = merge.relabel(q, found), merge.relabel(t, found)
        if strategy == "brute":
            q, t = (df.withColumn("cell", F.lit(0)) for df in (q, t))
        return cost.primitive_pairs(q, t)

    return run


def _regions_sql(name: str, k: int, n: int | None = None, more: str = "") -> str:
    """Regions by level counts: a node that queries enter and that holds fewer than k unites with its siblings."""
    d, n = PROFILES[name].d, n or DEFAULT_N[name]
    axes = ", ".join(f"c{i}" for i in range(d))
    up = ", ".join(f"c{i} >> up AS k{i}" for i in range(d))
    keys = ", ".join(f"k{i}" for i in range(d))
    parent = ", ".join(f"k{i} >> 1 AS k{i}" for i in range(d))
    same = " AND ".join(f"u.k{i} = (b.c{i} >> u.up)" for i in range(d))
    return f"{_points(name, more)}, base AS (SELECT {axes}, sum(t)::bigint AS t, sum(i)::bigint AS i FROM (SELECT {_cell(d, n, '')}, 1 AS t, 0 AS i FROM t UNION ALL SELECT {_cell(d, n, '')}, 0 AS t, 1 AS i FROM q) GROUP BY ALL), nodes AS (SELECT up, {keys}, sum(t) AS t, sum(i) AS i FROM (SELECT up, {up}, t, i FROM base, range(0, {n}) r(up)) GROUP BY ALL), united AS (SELECT DISTINCT up + 1 AS up, {parent} FROM nodes WHERE i > 0 AND t < {k}), regions AS (SELECT {', '.join(f'b.c{i}' for i in range(d))}, b.t, b.i, coalesce(max(u.up), 0) AS up FROM base b LEFT JOIN united u ON {same} GROUP BY ALL), named AS (SELECT up, {', '.join(f'c{i} >> up AS k{i}' for i in range(d))}, sum(t) AS t, sum(i) AS i FROM regions GROUP BY ALL)"


_add("pairs_brute_unif2", _pairs("brute"), f"{_points('unif2')} SELECT (SELECT count(*) FROM q) * (SELECT count(*) FROM t) AS pairs")
_add("pairs_grow_unif2", _pairs("grow"), _regions_sql("unif2", 5) + " SELECT sum(t * i)::bigint AS pairs FROM base")
_add("pairs_merge_unif2", _pairs("merge"), _regions_sql("unif2", 5) + " SELECT sum(t * i)::bigint AS pairs FROM named")


def _merge_stats(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, name)
        grid = _grid(name)
        found = merge.regions(grid.assign(train, "t"), grid.assign(query, "q"), grid, 5)
        return merge.stats(found, grid).select("merged_cells", "largest_merged", "merged_regions")

    return run


for _name in ("unif2", "skew3"):
    _d = PROFILES[_name].d
    _add(f"merge_stats_{_name}", _merge_stats(_name), _regions_sql(_name, 5) + f" SELECT coalesce(sum(1 << (up * {_d})::int), 0)::bigint AS merged_cells, coalesce(max(1 << (up * {_d})::int), 1)::bigint AS largest_merged, count(*) AS merged_regions FROM named WHERE up > 0")


def _distinct_axes(d: int, a: str = "", sep: str = ", ", fmt: str = "{a}c{i}") -> str:
    return sep.join(fmt.format(a=a, i=i) for i in range(d))


def _ball_sql(name: str, k: int, walls: bool = False, n: int | None = None, more: str = "") -> str:
    """Own lists, start radius, growths, radius and touched cells of every query, by the definitions alone.

    walls: cells reach as far as their walls; else as far as their points.
    """
    d, n = PROFILES[name].d, n or DEFAULT_N[name]
    m = 1 << n
    axes = _distinct_axes(d)
    low = [f"least(min(x{i}), c{i} / {m}.0::double)" if walls else f"min(x{i})" for i in range(d)]
    high = [f"greatest(max(x{i}), (c{i} + 1) / {m}.0::double)" if walls else f"max(x{i})" for i in range(d)]
    boxes = ", ".join(f"{low[i]} AS lo{i}, {high[i]} AS hi{i}" for i in range(d))
    gap = [f"greatest(lo{i} - h.x{i}, 0.0::double, h.x{i} - hi{i})" for i in range(d)]
    near = "sqrt(" + " + ".join(f"{g} * {g}" for g in gap) + ")"
    s = f"{0.5 / m!r}::double"
    return (
        f"{_points(name, more)}, qc AS (SELECT *, {_cell(d, n, '')} FROM q), tc AS (SELECT *, {_cell(d, n, '')} FROM t), "
        f"own AS (SELECT q.pid, {_dist(d)} AS dist FROM qc q JOIN tc t ON {_same_cell(d, 'q', 't')} QUALIFY row_number() OVER (PARTITION BY q.pid ORDER BY {_dist(d)}, t.tid) <= {k}), "
        f"mine AS (SELECT pid, count(*) AS held, max(dist) AS last FROM own GROUP BY pid), "
        f"h AS (SELECT qc.*, coalesce(held, 0) AS held, last FROM qc LEFT JOIN mine USING (pid)), "
        f"boxes AS (SELECT {axes}, count(*) AS n, {boxes} FROM tc GROUP BY {axes}), "
        f"near AS (SELECT h.pid, b.n, {_distinct_axes(d, 'b.')}, {_same_cell(d, 'h', 'b')} AS home, {near} AS near FROM h, boxes b), "
        f"need AS (SELECT pid, min(near) FILTER (sofar >= {k}) AS need FROM (SELECT pid, near, sum(n) OVER (PARTITION BY pid ORDER BY near RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sofar FROM near) GROUP BY pid), "
        f"start AS (SELECT h.*, need, CASE WHEN held > 0 THEN last ELSE {s} END AS r0 FROM h JOIN need USING (pid)), "
        f"grown AS (SELECT *, CASE WHEN held >= {k} THEN 0 ELSE ceil(greatest(0.0::double, need - r0) / {s}) END AS growths FROM start), "
        f"ball AS (SELECT *, r0 + {s} * growths AS r FROM grown), "
        f"touched AS (SELECT ball.pid, {_distinct_axes(d, 'near.')}, near.n FROM ball JOIN near USING (pid) WHERE NOT home AND near <= r * (1 + 1e-9::double) + 1e-12::double)"
    )


def _touch_lists_sql(name: str, k: int) -> str:
    """What touch growth finds: the best of the touched cells; complete lists only look inside their ball."""
    d = PROFILES[name].d
    seen = f"seen AS (SELECT b.pid, t.tid, {_dist(d, a='b')} AS dist FROM ball b JOIN tc t ON {_same_cell(d, 'b', 't')} UNION ALL SELECT b.pid, t.tid, {_dist(d, a='b')} AS dist FROM ball b JOIN touched u ON b.pid = u.pid JOIN tc t ON {_same_cell(d, 'u', 't')} WHERE b.held < {k} OR {_dist(d, a='b')} <= b.r * (1 + 1e-9::double) + 1e-12::double)"
    return f"{_ball_sql(name, k, walls=True)}, {seen}, nn AS (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY dist, tid) AS rank FROM seen QUALIFY rank <= {k})"


def _balls(name: str, column: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = _sides(spark, sf_dir, name)
        found = pipeline.search(query, train, 5, _grid(name))
        if column == "updates":
            return cost.updates_per_point(found).groupBy("updates").agg(F.count("*").alias("queries"))
        if column == "done":
            return found.balls.select("pid", "done", "growths")
        touched = found.balls.select("pid").join(found.probes.groupBy("pid").agg(F.count("*").alias("overlaps")), "pid", "left")
        return touched.select("pid", F.coalesce("overlaps", F.lit(0)).cast("long").alias("overlaps"))

    return run


def _inside_sql(d: int, n: int) -> str:
    m = 1 << n
    at = lambda x: f"least(greatest(floor(({x}) * {m} / 1.0::double), 0), {m - 1})::int"
    reach = "(r * (1 + 1e-9::double) + 1e-12::double)"
    return " AND ".join(f"{at(f'x{i} - {reach} - 0.0::double')} = c{i} AND {at(f'x{i} + {reach} - 0.0::double')} = c{i}" for i in range(d))


for _name in ("unif2", "skew2"):
    _per = f"{_ball_sql(_name, 5)}, per AS (SELECT ball.pid, count(touched.pid) AS n_touched FROM ball LEFT JOIN touched USING (pid) GROUP BY ball.pid)"
    _add(f"overlaps_{_name}", _balls(_name, "overlaps"), f'{_per} SELECT pid, n_touched AS "overlaps" FROM per')
    _add(f"updates_{_name}", _balls(_name, "updates"), f"{_per} SELECT n_touched + 1 AS updates, count(*) AS queries FROM per GROUP BY ALL")
    _add(f"done_flag_{_name}", _balls(_name, "done"), f"{_ball_sql(_name, 5)} SELECT pid, held >= 5 AND {_inside_sql(2, DEFAULT_N[_name])} AS done, growths::bigint AS growths FROM ball")


def _measures_sql(name: str, k: int, more: str = "", n: int | None = None) -> str:
    d, n = PROFILES[name].d, n or DEFAULT_N[name]
    seen = f"seen AS (SELECT b.pid, {_dist(d, a='b')} AS dist FROM ball b JOIN tc t ON {_same_cell(d, 'b', 't')} WHERE b.held < {k} UNION ALL SELECT b.pid, {_dist(d, a='b')} AS dist FROM ball b JOIN touched u ON b.pid = u.pid JOIN tc t ON {_same_cell(d, 'u', 't')} WHERE b.held < {k})"
    kth = f"kth AS (SELECT pid, dist FROM seen QUALIFY row_number() OVER (PARTITION BY pid ORDER BY dist) = {k})"
    again = "again AS (SELECT near.n FROM kth JOIN ball USING (pid) JOIN near USING (pid) WHERE NOT home AND dist > r AND near > r AND near <= dist * (1 + 1e-9::double) + 1e-12::double)"
    parts = {
        "pairs_primitive": "SELECT coalesce(sum(n), 0) FROM near WHERE home",
        "pairs_probe": "SELECT coalesce(sum(n), 0) FROM touched",
        "pairs_recheck": "SELECT coalesce(sum(n), 0) FROM again",
        "overlaps": "SELECT count(*) FROM touched",
        "growths": "SELECT coalesce(sum(growths), 0) FROM ball",
        "short_queries": f"SELECT count(*) FROM ball WHERE held < {k}",
        "done_queries": f"SELECT count(*) FROM ball WHERE held >= {k} AND {_inside_sql(d, n)}",
        "updates": "SELECT (SELECT count(*) FROM ball) + (SELECT count(*) FROM touched)",
        "occupied_cells": "SELECT count(*) FROM boxes",
        "list_entries": "SELECT coalesce(sum(held), 0) FROM ball",
    }
    rows = " UNION ALL ".join(f"SELECT '{c}' AS measure, ({q})::bigint AS value" for c, q in parts.items())
    return f"{_ball_sql(name, k, n=n, more=more)}, {seen}, {kth}, {again} {rows}"


_add("measures_skew2", lambda spark, sf_dir: cost.measures(pipeline.search(*reversed(_sides(spark, sf_dir, "skew2")), 5, _grid("skew2"))), _measures_sql("skew2", 5))


def _touch_skew2(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "skew2")
    rows = pipeline.all_knn(query, train, 5, _grid("skew2"), growth="touch")
    return rows.select("pid", F.col("rank").cast("int").alias("rank"), "tid", _micro())


_add("touch_allknn_skew2", _touch_skew2, _touch_lists_sql("skew2", 5) + " SELECT pid, rank::int AS rank, tid, floor(dist * 1e6)::bigint AS dist6 FROM nn")


def _recall_touch(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "skew2")
    seen = pipeline.shared_places(query, 2)
    asked = query if seen is None else seen.drop("copies")
    run = lambda **o: pipeline.search(asked, train, 5, _grid("skew2"), **o).final
    return quality.recall(run(growth="touch"), run(strategy="brute"), seen).select("queries", "exact_lists", F.round(F.col("recall") * MICRO).cast("long").alias("recall6"))


_EXACT5 = f"exact AS (SELECT q.pid, t.tid, row_number() OVER (PARTITION BY q.pid ORDER BY {_dist(2)}, t.tid) AS rank FROM q, t QUALIFY rank <= 5)"
_add("recall_touch_skew2", _recall_touch, f"{_touch_lists_sql('skew2', 5)}, {_EXACT5}, each_list AS (SELECT e.pid, count(n.tid) / count(*) AS share, count(*) FILTER (n.rank = e.rank) = count(*) AS same FROM exact e LEFT JOIN nn n ON n.pid = e.pid AND n.tid = e.tid GROUP BY e.pid) SELECT count(*) AS queries, count(*) FILTER (same) AS exact_lists, round(avg(share) * 1e6)::bigint AS recall6 FROM each_list")


# ---- workloads --------------------------------------------------------------------------


def _swept(parts: dict[tuple, str], names: tuple[str, ...]) -> str:
    """One statement from a statement for each value of the parameters."""
    tagged = (", ".join(f"{v!r}::{'varchar' if isinstance(v, str) else 'int' if isinstance(v, int) else 'double'} AS {c}" for c, v in zip(names, key, strict=True)) for key in parts)
    return " UNION ALL ".join(f"SELECT {tags}, * FROM ({sql})" for tags, sql in zip(tagged, parts.values(), strict=True))


_PAIRS = {"grow": " SELECT coalesce(sum(t * i), 0)::bigint AS pairs FROM base", "merge": " SELECT coalesce(sum(t * i), 0)::bigint AS pairs FROM named"}
for _name, _ns in (("skew1", (4, 8, 11)), ("skew2", (2, 4, 6)), ("skew3", (1, 3, 4)), ("unif1", (4, 7, 10)), ("unif2", (2, 4, 6)), ("unif3", (1, 3, 4))):
    _add(f"sweep_n_{_name}", lambda spark, sf_dir, name=_name, ns=_ns: workloads.own_cell_pairs(spark, sf_dir, name, ns), _swept({(n, m): _regions_sql(_name, 5, n) + _PAIRS[m] for n in _ns for m in _PAIRS}, ("n", "method")))
_STATS = " SELECT coalesce(sum(1 << (up * {d})::int), 0)::bigint AS merged_cells, coalesce(max(1 << (up * {d})::int), 1)::bigint AS largest_merged, count(*) AS merged_regions, floor(coalesce(sum(1 << (up * {d})::int), 0) * 100.0::double / {total}.0::double * 1e6)::bigint AS pct6 FROM named WHERE up > 0"


def _merge_table(name: str, ks=(5,), fs=(1.0,)) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = workloads.merge_statistics(spark, sf_dir, name, ks, fs)
        return out.select("k", "f", "merged_cells", "largest_merged", "merged_regions", F.floor(F.col("pct_of_cells") * MICRO).cast("long").alias("pct6"))

    return run


for _name in ("skew3", "unif3"):
    _stats = _STATS.format(d=3, total=1 << 3 * DEFAULT_N[_name])
    _add(f"merge_table_k_{_name}", _merge_table(_name, workloads.KS), _swept({(k, 1.0): _regions_sql(_name, k) + _stats for k in workloads.KS}, ("k", "f")))
    _fs = workloads.FRACTIONS[:4]
    _add(f"merge_table_f_{_name}", _merge_table(_name, (5,), _fs), _swept({(5, f): _regions_sql(_name, 5, more=f"AND pid % 100 < {round(100 * f)}") + _stats for f in _fs}, ("k", "f")))

_COUNTED = lambda df, *names: df.select(*names, "measure", "value")
_add("sweep_k_skew2", lambda spark, sf_dir: _COUNTED(workloads.neighbours(spark, sf_dir, "skew2", strategies=("grow",)), "k"), _swept({(k,): _measures_sql("skew2", k) for k in workloads.KS}, ("k",)))
_add("sweep_d_unif", lambda spark, sf_dir: _COUNTED(workloads.dimensions(spark, sf_dir, "unif", 20, ("grow",)), "profile"), _swept({(f"unif{d}",): _measures_sql(f"unif{d}", 20) for d in (1, 2, 3)}, ("profile",)))
_add("sweep_f_unif3", lambda spark, sf_dir: _COUNTED(workloads.scale(spark, sf_dir, "unif3", (0.2, 0.6), strategies=("grow",)), "f"), _swept({(f,): _measures_sql("unif3", 5, f"AND pid % 100 < {round(100 * f)}") for f in (0.2, 0.6)}, ("f",)))
_add("times_unif2", lambda spark, sf_dir: workloads.total_times(spark, sf_dir, "unif2"))
_add("phase_times_unif2", lambda spark, sf_dir: workloads.phase_times(spark, sf_dir, "unif2", (5,)))


def _self_part2(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = joins.all_knn_self(PROFILES["part2"].points(spark, sf_dir), 2, 5, _grid("part2"))
    return rows.select("pid", F.col("rank").cast("int").alias("rank"), "tid", _micro())


_SELF = f"WITH p AS ({PROFILES['part2'].sql()}), pairs AS (SELECT q.pid, t.pid AS tid, {_dist(2)} AS dist FROM p q, p t WHERE q.pid <> t.pid), nn AS (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY dist, tid) AS rank FROM pairs QUALIFY rank <= 5)"
_add("allknn_self_part2", _self_part2, _SELF + " SELECT pid, rank::int AS rank, tid, floor(dist * 1e6)::bigint AS dist6 FROM nn")


def _cloak(spark: SparkSession, sf_dir: str) -> DataFrame:
    box = joins.cloak(PROFILES["part2"].points(spark, sf_dir), 2, 5, _grid("part2"))
    return box.select("pid", *[_micro(f"{n}{i}") for i in range(2) for n in ("lo", "hi")])


_add("cloak_part2", _cloak, _SELF + ", m AS (SELECT pid, tid FROM nn UNION ALL SELECT pid, pid FROM p) SELECT m.pid, " + ", ".join(f"floor({f}(x{i}) * 1e6)::bigint AS {n}{i}6" for i in range(2) for n, f in (("lo", "min"), ("hi", "max"))) + " FROM m JOIN p ON p.pid = m.tid GROUP BY m.pid")


def _one_point(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, _ = _sides(spark, sf_dir, "unif2")
    return joins.knn([0.5, 0.5], train, 10).select(F.col("rank").cast("int").alias("rank"), "tid", _micro())


_add("knn_one_point", _one_point, f"{_points('unif2')}, o AS (SELECT 0.5::double AS x0, 0.5::double AS x1) SELECT row_number() OVER (ORDER BY {_dist(2, a='o')}, tid)::int AS rank, tid, floor({_dist(2, a='o')} * 1e6)::bigint AS dist6 FROM t, o QUALIFY rank <= 10")


def _within(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "unif2")
    return joins.within(query, train, 0.02, _grid("unif2")).select("pid", "tid", _micro())


_add("within_radius_unif2", _within, f"{_points('unif2')} SELECT pid, tid, floor({_dist(2)} * 1e6)::bigint AS dist6 FROM q, t WHERE {_dist(2)} <= 0.02::double")


def _nearest_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, query = _sides(spark, sf_dir, "skew1")
    return joins.nearest_1d(query, train).select("pid", "tid", _micro())


_add("nearest_1d_skew1", _nearest_line, _ranked("skew1", 1) + " SELECT pid, tid, floor(dist * 1e6)::bigint AS dist6 FROM nn")


def _join_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, s = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("customer", "supplier"))
    grid = GridSpec.quantile(s.select(F.col("s_acctbal").alias("t0")), [16])
    out = joins.knn_join(c, s, "c_custkey", "s_suppkey", [("c_acctbal", "s_acctbal")], 3, grid)
    return out.select("l_c_custkey", "l_c_name", F.col("rank").cast("int").alias("rank"), "r_s_suppkey", "r_s_name", _micro())


_add("knn_join_customer_supplier", _join_customers, "WITH x AS (SELECT c_custkey AS l_c_custkey, c_name AS l_c_name, s_suppkey AS r_s_suppkey, s_name AS r_s_name, sqrt((c_acctbal - s_acctbal) * (c_acctbal - s_acctbal)) AS dist FROM customer, supplier) SELECT l_c_custkey, l_c_name, row_number() OVER (PARTITION BY l_c_custkey ORDER BY dist, r_s_suppkey)::int AS rank, r_s_suppkey, r_s_name, floor(dist * 1e6)::bigint AS dist6 FROM x QUALIFY rank <= 3")


def _scaled(f: float) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, query = split(fraction(PROFILES["unif3"].points(spark, sf_dir), f), 3)
        return pipeline.all_knn(query, train, 5, _grid("unif3")).select("pid", F.col("rank").cast("int").alias("rank"), "tid", _micro())

    return run


for _f in (0.2, 0.4, 0.6, 0.8):
    _add(f"scale_F_{round(10 * _f)}_unif3", _scaled(_f), _lists_sql("unif3", 5, more=f"AND pid % 100 < {round(100 * _f)}"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Certified classification of the skewed 3-D points, k = 10."""
    return _classify("skew3", 10)(spark, sf_dir)


__all__ = ["ORACLE", "QUERIES", "flagship"]

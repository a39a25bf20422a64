"""The named runs of every method, variant, baseline, measure and workload: name -> (query, reference SQL or None)."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce
from math import pi

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine import reference_sql as R
from inverse_engine.functions.geometry import columns, coordinates, max_dist2_of_set, orthant
from inverse_engine.operators import eps_range, framework, knn, skyline
from inverse_engine.operators.common import gathered
from inverse_engine.plans import accesses
from inverse_engine.plans.blocks import build_index, page_model, rollup_blocks
from inverse_engine.plans.store import stored, together
from inverse_engine.sources import query_sets
from inverse_engine.sources.points import fixture, lattice, make_points, read_table

Query = Callable[[SparkSession, str], DataFrame]
CASES: dict[str, tuple[Query, str | None]] = {}

#: Workload values of the experiments (fixed values): radius, k, members, extent; the first of each pair below is the default.
EPS, EPS_SWEEP = 0.06, (0.04, 0.05, 0.06, 0.07, 0.08, 0.09, 0.1)
K, K_SWEEP = 100, (50, 100, 150, 200, 250)
M, M_SWEEP = 10, (1, 3, 5, 10, 15, 20, 25, 30, 35)
EXTENT, EXTENT_SWEEP = 0.0004, (0.0001, 0.0002, 0.0003, 0.0004, 0.0005, 0.0006)
#: Extent for tables of fewer than 20,000 points.
WIDE = 0.005


def case(name: str, run: Query, sql: str | None) -> None:
    CASES[name] = (run, sql)


def _sets(points: DataFrame, n: int, m: int, extent: float | None, seed: int = 0) -> DataFrame:
    return query_sets.neighbour_query_sets(points, n, m, seed) if extent is None else query_sets.sample_query_sets(points, n, m, extent, seed)


def method(name: str, table: str, predicate, n: int, m: int, extent: float | None, sql: str, oracle: bool = True, candidates: str | None = None, indexed: bool = False, **options) -> None:
    """A run of one predicate on one fixture. candidates: another fixture, or lattice-<steps>."""
    d = R.point_sql(table)[1]
    pool_sql = None
    if candidates:
        pool_sql = R.lattice_sql(d, int(candidates.split("-")[1])) if candidates.startswith("lattice") else R.point_sql(candidates)[0]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = fixture(spark, sf_dir, table)
        pool = None
        if candidates:
            pool = lattice(spark, d, int(candidates.split("-")[1])) if candidates.startswith("lattice") else fixture(spark, sf_dir, candidates)
        index = build_index(points, 256) if indexed else None
        return framework.inverse(points, _sets(points, n, m, extent), predicate, candidates=pool, index=index, **options)

    case(name, run, R.with_sql(table, R.sets_sql(d, n, m, extent), d, pool_sql) + sql if oracle else None)


def sweep(name: str, values, make: Callable[[object], tuple], oracle: bool = True) -> None:
    """One run for each value, tagged by its place in the sweep: (v, set_id, n) with the number of results of each set that has any."""
    parts = [make(v) for v in values]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        def one(i: int) -> DataFrame:
            table, predicate, n, m, extent, _ = parts[i]
            points = fixture(spark, sf_dir, table)
            return framework.inverse(points, _sets(points, n, m, extent), predicate).groupBy("set_id").agg(F.count("*").alias("n")).select(F.lit(i).alias("v"), "set_id", "n")

        return reduce(DataFrame.unionByName, together(spark, [partial(one, i) for i in range(len(parts))], "sweep-counts"))

    pieces = []
    for i, (table, _, n, m, extent, sql) in enumerate(parts):
        d = R.point_sql(table)[1]
        pieces.append(f"SELECT {i} AS v, set_id, count(*) AS n FROM ({R.with_sql(table, R.sets_sql(d, n, m, extent), d)}{sql}) GROUP BY set_id")
    case(name, run, " UNION ALL ".join(f"({p})" for p in pieces) if oracle else None)


E_, N_, S_ = framework.EpsRange, framework.Nearest, framework.DynamicSkyline()

# Range queries.
for label, options in {"joint": {"indexed": True}, "naive": {"strategy": "naive"}, "single": {"strategy": "single"}, "brute": {"strategy": "brute"}}.items():
    method(f"eps_inverse_{label}", "line3", E_(EPS), 5, 5, EXTENT, R.eps_sql(3, EPS), **options)
method("eps_inverse_m1", "line3", E_(EPS), 4, 1, EXTENT, R.eps_sql(3, EPS))
method("eps_reverse_m1", "line3", E_(EPS), 4, 1, EXTENT, R.eps_sql(3, EPS), strategy="naive")
method("eps_inverse_open", "part2", E_(0.1, closed=False), 4, 4, WIDE, R.eps_sql(2, 0.1, closed=False))
method("eps_inverse_incl_q", "line3", E_(EPS), 5, 5, EXTENT, R.eps_sql(3, EPS, keep_queries=True), include_query_objects=True)
method("eps_bichromatic", "part2", E_(0.1), 4, 4, WIDE, R.eps_sql(2, 0.1, keep_queries=True), candidates="customer2")
method("eps_region_lattice", "part2", E_(0.1), 3, 4, WIDE, R.eps_sql(2, 0.1, keep_queries=True), candidates="lattice-64")
method("eps_orders", "orders2", E_(0.1), 4, 4, WIDE, R.eps_sql(2, 0.1), indexed=True)
method("eps_clustered", "customer3", E_(0.1), 4, 3, WIDE, R.eps_sql(3, 0.1), indexed=True)
sweep("eps_sweep_eps", EPS_SWEEP, lambda v: ("line3", E_(v), 4, M, EXTENT, R.eps_sql(3, v)))
sweep("eps_sweep_m", M_SWEEP, lambda v: ("line3", E_(EPS), 4, v, EXTENT, R.eps_sql(3, EPS)))
# The ball's volume stays that of the default radius in three dimensions.
_ball = {2: pi, 3: 4 / 3 * pi, 4: pi**2 / 2, 5: 8 / 15 * pi**2}
_radius = {d: (_ball[3] * EPS**3 / _ball[d]) ** (1 / d) for d in _ball}
sweep("eps_sweep_d", (2, 3, 4, 5), lambda d: (f"line{d}", E_(_radius[d]), 4, M, EXTENT, R.eps_sql(d, _radius[d])))
sweep("eps_sweep_extent", EXTENT_SWEEP, lambda v: ("line3", E_(EPS), 4, M, v, R.eps_sql(3, EPS)))


def _vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    first = query_sets.anchors(rows.select("id"), 6, 0).select((F.col("set_id") % 2).cast("long").alias("set_id"), F.col("anchor").alias("q_id"))
    return eps_range.inverse_eps_vectors(rows, first, 1.3)


case(
    "eps_embeddings64",
    _vectors,
    f"WITH pts AS ({R.point_sql('emb64')[0]}), q AS (SELECT CAST((row_number() OVER (ORDER BY {R.draw_sql(0)}, id) - 1) % 2 AS BIGINT) AS set_id, id AS q, {', '.join(f'x{i}' for i in range(64))} FROM pts ORDER BY {R.draw_sql(0)}, id LIMIT 6), "
    f"pool AS (SELECT * FROM pts), ids AS (SELECT set_id, count(*) AS m FROM q GROUP BY set_id) {R.eps_sql(64, 1.3)}",
)


def _per_set_eps(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    sets = _sets(points, 5, 5, EXTENT).withColumn("eps", F.lit(0.04) + F.col("set_id") * F.lit(0.01))
    return framework.inverse(points, sets, E_())


_line3 = R.with_sql("line3", R.sets_sql(3, 5, 5, EXTENT), 3)
_eps_of_set = "(CAST(0.04 AS DOUBLE) + q.set_id * CAST(0.01 AS DOUBLE))"
case("eps_per_set_radius", _per_set_eps, _line3 + R.eps_sql(3, 0, limit=f"{_eps_of_set} * {_eps_of_set}"))


def _forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    probes = query_sets.anchors(points, 6, 0).select(F.col("anchor").alias("id"), *[F.col(f"a{i}").alias(f"x{i}") for i in range(3)])
    return eps_range.eps_forward(points, probes, EPS)


case("eps_forward", _forward, R.with_sql("line3", R.sets_sql(3, 6, 1, EXTENT), 3) + f"SELECT q.q AS probe, p.id FROM pts p JOIN q ON {R.d2_sql('p', 'q', 3)} <= CAST({EPS} AS DOUBLE) * CAST({EPS} AS DOUBLE)")


def _window(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    rows = eps_range.eps_window(gathered(points, _sets(points, 5, 5, EXTENT)).withColumn("eps", F.lit(EPS)), 3)
    ends = [F.round(F.get(c, F.lit(i)), 9).alias(f"{c}{i}") for i in range(3) for c in ("lo", "hi")]
    return rows.select("set_id", *ends)


case("eps_window", _window, _line3 + "SELECT set_id, " + ", ".join(f"round(max(x{i}) - {EPS}, 9) AS lo{i}, round(min(x{i}) + {EPS}, 9) AS hi{i}" for i in range(3)) + " FROM q GROUP BY set_id")


def _validate(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    rows = gathered(points, _sets(points, 40, 5, EXTENT)).withColumn("eps", F.lit(0.03))
    return eps_range.eps_validate(rows, 3).select("set_id", "alive")


case("eps_validate_empty", _validate, R.with_sql("line3", R.sets_sql(3, 40, 5, EXTENT), 3) + f"SELECT q.set_id, max({R.d2_sql('q', 'z', 3)}) <= CAST(0.03 AS DOUBLE) * CAST(0.03 AS DOUBLE) * 4.0 AS alive FROM q JOIN q z ON z.set_id = q.set_id GROUP BY q.set_id")

# Nearest-neighbour queries.
for label, options in {"joint": {"indexed": True}, "naive": {"strategy": "naive"}, "single": {"strategy": "single"}, "brute": {"strategy": "brute"}}.items():
    method(f"knn_inverse_{label}", "part2", N_(50), 4, 4, WIDE, R.knn_sql(2, 50), **options)
method("knn_reverse_m1", "part2", N_(20), 4, 1, WIDE, R.knn_sql(2, 20))
method("knn_clustered", "customer3", N_(50), 4, 3, None, R.knn_sql(3, 50), indexed=True)
method("knn_duplicates_part", "part2", N_(8), 6, 3, None, R.knn_sql(2, 8))
method("knn_incl_q", "part2", N_(50), 4, 4, WIDE, R.knn_sql(2, 50, keep_queries=True), include_query_objects=True)
method("knn_bichromatic", "part2", N_(50), 4, 4, WIDE, R.knn_sql(2, 50, mono=False), candidates="customer2")
method("knn_region_lattice", "part2", N_(50), 3, 4, WIDE, R.knn_sql(2, 50, mono=False), candidates="lattice-32")
method("knn_lineitem", "line3", N_(K), 5, 5, EXTENT, R.knn_bounded_sql(3, K, 400), indexed=True)
method("knn_lineitem_m10", "line3", N_(K), 3, M, EXTENT, R.knn_bounded_sql(3, K, 400), indexed=True)
sweep("knn_sweep_k", K_SWEEP, lambda v: ("part2", N_(v), 3, 4, WIDE, R.knn_sql(2, v)))
sweep("knn_sweep_m", (1, 3, 5, 10), lambda v: ("part2", N_(50), 3, v, WIDE, R.knn_sql(2, 50)))
sweep("knn_sweep_d", (2, 3, 4, 5), lambda v: (f"emb{v}", N_(50), 3, 3, None, R.knn_sql(v, 50)))
sweep("knn_sweep_extent", (0.0025, 0.005, 0.0075, 0.01), lambda v: ("part2", N_(50), 3, 4, v, R.knn_sql(2, 50)))


def _knn_variant(**options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = fixture(spark, sf_dir, "part2")
        return knn.inverse_knn(points, _sets(points, 4, 4, WIDE), 50, **options)

    return run


_part2 = R.with_sql("part2", R.sets_sql(2, 4, 4, WIDE), 2)
case("knn_refine_by_search", _knn_variant(refine="search"), _part2 + R.knn_sql(2, 50))
case("knn_refine_by_count", _knn_variant(refine="range_count"), _part2 + R.knn_sql(2, 50))
case("knn_no_hull", _knn_variant(hull=False), _part2 + R.knn_sql(2, 50))


def _knn_forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "orders2")
    probes = query_sets.anchors(points, 8, 0).select(F.col("anchor").alias("id"), "a0", "a1").toDF("id", "x0", "x1")
    return knn.knn(points, probes, 10).select("probe", "id", "rank")


case("knn_forward", _knn_forward, R.with_sql("orders2", R.sets_sql(2, 8, 1, WIDE), 2) + f"SELECT probe, id, CAST(r AS INTEGER) AS rank FROM (SELECT q.q AS probe, p.id, row_number() OVER (PARTITION BY q.q ORDER BY {R.d2_sql('p', 'q', 2)}, p.id) AS r FROM pts p JOIN q ON p.id <> q.q) WHERE r <= 10")


def _knn_validate(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    return knn.knn_validate(gathered(points, _sets(points, 12, 12, WIDE)).withColumn("k", F.lit(8))).select("set_id", "alive")


case("knn_validate", _knn_validate, R.with_sql("part2", R.sets_sql(2, 12, 12, WIDE), 2) + "SELECT set_id, m <= 8 AS alive FROM ids")


def _furthest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from inverse_engine.functions.geometry import furthest

    points = fixture(spark, sf_dir, "part2")
    rows = F.broadcast(gathered(points, _sets(points, 4, 4, WIDE)))
    return points.join(rows).select("set_id", "id", furthest(columns(coordinates(2)), F.col("qs"), 2)["q"].alias("q_ref"))


case("knn_furthest_query", _furthest, _part2 + f"SELECT q.set_id, p.id, max({{'d': {R.d2_sql('p', 'q', 2)}, 'q': q.q}}).q AS q_ref FROM pts p CROSS JOIN q GROUP BY q.set_id, p.id")


def _reduced(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Objects that pass the reduced k of every single member among the points without the other members."""
    points = fixture(spark, sf_dir, "part2")
    return knn.reduced_k_candidates(points, _sets(points, 3, 4, WIDE), 50)


_p2s3 = R.with_sql("part2", R.sets_sql(2, 3, 4, WIDE), 2)
case(
    "knn_reduced_k_candidates",
    _reduced,
    _p2s3
    + "SELECT set_id, id FROM (SELECT s.set_id, c.id, s.m, q.q, count(o.id) AS n FROM pts c CROSS JOIN ids s JOIN q ON q.set_id = s.set_id LEFT JOIN pts o ON o.id <> c.id AND NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = o.id) "
    + f"AND ({R.d2_sql('o', 'c', 2)} < {R.d2_sql('q', 'c', 2)} OR ({R.d2_sql('o', 'c', 2)} = {R.d2_sql('q', 'c', 2)} AND o.id < q.q)) WHERE NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = c.id) GROUP BY s.set_id, c.id, s.m, q.q) WHERE n < 50 - m + 1 GROUP BY set_id, id, m HAVING count(*) = m",
)


def _hull_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "orders2")
    return knn.hull_members(points, gathered(points, _sets(points, 4, 3, WIDE)), 2).groupBy("set_id").agg(F.count("*").alias("h"))


def _cross(a: str, b: str, c: str) -> str:
    return f"(({b}.x0 - {a}.x0) * ({c}.x1 - {a}.x1) - ({b}.x1 - {a}.x1) * ({c}.x0 - {a}.x0))"


# For three members the hull is one triangle: inside means one sign of three cross products.
case("knn_hull_count_2d", _hull_count, R.with_sql("orders2", R.sets_sql(2, 4, 3, WIDE), 2) + f"SELECT a.set_id, count(*) AS h FROM q a JOIN q b ON b.set_id = a.set_id AND b.q > a.q JOIN q c ON c.set_id = a.set_id AND c.q > b.q JOIN pts p ON p.id NOT IN (a.q, b.q, c.q) WHERE ({_cross('a', 'b', 'p')} > 0 AND {_cross('b', 'c', 'p')} > 0 AND {_cross('c', 'a', 'p')} > 0) OR ({_cross('a', 'b', 'p')} < 0 AND {_cross('b', 'c', 'p')} < 0 AND {_cross('c', 'a', 'p')} < 0) GROUP BY a.set_id")

# Dynamic skyline queries.
for label, options in {"joint": {"indexed": True}, "naive": {"strategy": "naive"}, "single": {"strategy": "single"}, "brute": {"strategy": "brute"}}.items():
    method(f"sky_inverse_{label}", "customer3", S_, 4, 2, None, R.sky_sql(3), **options)
method("sky_reverse_m1", "part2", S_, 4, 1, None, R.sky_sql(2))
method("sky_users", "users4", S_, 4, 4, None, R.sky_sql(4))
method("sky_supplier", "supplier3", S_, 5, 3, None, R.sky_sql(3))
method("sky_bichromatic", "part2", S_, 3, 1, None, R.sky_sql(2, mono=False), candidates="customer2")
method("sky_region_lattice", "part2", S_, 3, 1, None, R.sky_sql(2, mono=False), candidates="lattice-32")
method("sky_incl_m1_orders", "orders2", S_, 1, 2, None, R.sky_sql(2))
sweep("sky_sweep_m", (1, 2, 3, 4), lambda v: ("emb8", S_, 2, v, None, R.sky_sql(8)))
sweep("sky_sweep_extent", (0.005, 0.02, 0.05), lambda v: ("customer3", S_, 3, 2, v, R.sky_sql(3)))
sweep("sky_sweep_d", (2, 3, 4, 5), lambda v: (f"emb{v}", S_, 4, 2, None, R.sky_sql(v)))


def _sky_variant(**options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = fixture(spark, sf_dir, "customer3")
        return skyline.inverse_dynamic_skyline(points, _sets(points, 4, 2, None), **options)

    return run


_cust3 = R.with_sql("customer3", R.sets_sql(3, 4, 2, None), 3)
case("sky_refine_dsl", _sky_variant(refine="dsl"), _cust3 + R.sky_sql(3))
case("sky_refine_mbr", _sky_variant(refine="mbr"), _cust3 + R.sky_sql(3))
case("sky_static", lambda spark, sf: skyline.skyline(fixture(spark, sf, "customer3")).select("id"), f"WITH pts AS ({R.point_sql('customer3')[0]}) SELECT id FROM pts a WHERE NOT EXISTS (SELECT 1 FROM pts o WHERE o.x0 <= a.x0 AND o.x1 <= a.x1 AND o.x2 <= a.x2 AND (o.x0 < a.x0 OR o.x1 < a.x1 OR o.x2 < a.x2))")


def _sky_dynamic(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    return skyline.dynamic_skyline(points, query_sets.anchors(points, 5, 0).select(F.col("anchor").alias("id"), F.col("a0").alias("x0"), F.col("a1").alias("x1")))


case("sky_dynamic", _sky_dynamic, R.with_sql("part2", R.sets_sql(2, 5, 1, None), 2) + f"SELECT q.q AS probe, p.id FROM pts p JOIN q ON p.id <> q.q EXCEPT SELECT q.q, p.id FROM pts p JOIN q ON p.id <> q.q JOIN pts o ON o.id <> q.q AND {R.dominates_sql('o', 'p', 'q', 2)}")


def _rds(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    return skyline.rds_candidates(points, gathered(points, _sets(points, 4, 1, None)))


_side = lambda p: "(" + " + ".join(f"CASE WHEN {p}.x{i} >= q.x{i} THEN {1 << i} ELSE 0 END" for i in range(2)) + ")"
_p2n1 = R.with_sql("part2", R.sets_sql(2, 4, 1, None), 2)
case("sky_orthant_candidates", _rds, _p2n1 + f"SELECT q.set_id, p.id FROM pts p JOIN q ON p.id <> q.q EXCEPT SELECT q.set_id, p.id FROM pts p JOIN q ON p.id <> q.q JOIN pts o ON o.id <> q.q AND {_side('o')} = {_side('p')} AND {R.dominates_sql('o', 'p', 'q', 2)}")


def _sky_validate(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    return skyline.sky_validate(gathered(points, _sets(points, 12, 12, 0.02)), 2).select("set_id", "alive")


_full = " AND ".join(f"bool_or(z.x0 {a} q.x0 AND z.x1 {b} q.x1)" for a in (">=", "<=") for b in (">=", "<="))
case("sky_validate_orthants", _sky_validate, R.with_sql("part2", R.sets_sql(2, 12, 12, 0.02), 2) + f"SELECT ids.set_id, NOT coalesce(bool_or(f), false) AS alive FROM ids LEFT JOIN (SELECT q.set_id, q.q, {_full} AS f FROM q JOIN q z ON z.set_id = q.set_id AND (z.x0 <> q.x0 OR z.x1 <> q.x1) GROUP BY q.set_id, q.q) g ON g.set_id = ids.set_id GROUP BY ids.set_id")


def _pairs(stairs: bool) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = fixture(spark, sf_dir, "part2")
        rows = gathered(points, _sets(points, 4, 4, 0.02))
        if not stairs:
            return skyline.sky_query_prune(points, rows, 2)
        own = F.exists("qs", lambda q: q["q"] == F.col("id"))
        both = F.broadcast(rows.join(skyline.staircases(rows), "set_id"))
        return points.join(both, ~own & ~skyline.staircase_pruned(columns(coordinates(2)))).select("set_id", "id")

    return run


_p2w = R.with_sql("part2", R.sets_sql(2, 4, 4, 0.02), 2)
_survive = _p2w + f"SELECT s.set_id, p.id FROM pts p CROSS JOIN ids s WHERE NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = p.id) EXCEPT SELECT q.set_id, p.id FROM pts p CROSS JOIN q JOIN q o ON o.set_id = q.set_id AND o.q <> q.q AND {R.dominates_sql('o', 'q', 'p', 2)}"
case("sky_pair_prune_survivors", _pairs(False), _survive)
case("sky_staircase_2d", _pairs(True), _survive)

# Extensions.


def _topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    weights = lattice(spark, 2, 12).toDF("id", "w0", "w1")
    top = points.withColumn("s", F.col("x0") + F.col("x1")).orderBy(F.desc("s"), "id").limit(4).select(F.lit(0).cast("long").alias("set_id"), F.col("id").alias("q_id"))
    return framework.inverse_topk(points, weights, top, 40)


case(
    "topk_inverse",
    _topk,
    f"WITH pts AS ({R.point_sql('part2')[0]}), w AS ({R.lattice_sql(2, 12)}), q AS (SELECT id, x0, x1 FROM pts ORDER BY x0 + x1 DESC, id LIMIT 4), ranked AS (SELECT w.id AS wid, p.id, row_number() OVER (PARTITION BY w.id ORDER BY w.x0 * p.x0 + w.x1 * p.x1 DESC, p.id) AS r FROM w CROSS JOIN pts p) "
    "SELECT CAST(0 AS BIGINT) AS set_id, wid AS id FROM ranked WHERE r <= 40 AND id IN (SELECT id FROM q) GROUP BY wid HAVING count(*) = 4",
)


def _excluded(predicate) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = fixture(spark, sf_dir, "part2")
        drawn = _sets(points, 4, 4, WIDE)
        place = F.row_number().over(Window.partitionBy("set_id").orderBy("q_id"))
        split = drawn.withColumn("r", place)
        return framework.inverse(points, split.where("r > 1").drop("r"), predicate, exclude_sets=split.where("r = 1").drop("r"))

    return run


_split = f"WITH pts AS MATERIALIZED ({R.point_sql('part2')[0]}), a AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY q) AS r FROM ({R.sets_sql(2, 4, 4, WIDE)})), pool AS (SELECT * FROM pts), "
for label, predicate, sql in (("eps", E_(0.08), R.eps_sql(2, 0.08)), ("knn", N_(30), R.knn_sql(2, 30))):
    yes = f"SELECT * FROM (WITH q AS (SELECT set_id, q, x0, x1 FROM a WHERE r > 1), ids AS (SELECT set_id, count(*) AS m FROM q GROUP BY set_id) {sql})"
    no = f"SELECT * FROM (WITH q AS (SELECT set_id, q, x0, x1 FROM a WHERE r = 1), ids AS (SELECT set_id, count(*) AS m FROM q GROUP BY set_id) {sql})"
    case(f"excluded_members_{label}", _excluded(predicate), _split + f"yes AS ({yes}), no AS ({no}) SELECT set_id, id FROM yes EXCEPT SELECT set_id, id FROM no")


# Measures and the parts around the methods.


def _rounded(name: str) -> tuple[Query, str]:
    sql, d = R.point_sql(name)
    run = lambda spark, sf: fixture(spark, sf, name).select("id", *[F.round(f"x{i}", 9).alias(f"x{i}") for i in range(d)])
    return run, f"SELECT id, {', '.join(f'round(x{i}, 9) AS x{i}' for i in range(d))} FROM ({sql})"


for label, name in {"normalise_minmax": "line5", "user_profile_points": "users4", "doc_feature_points": "doc3", "conv_feature_points": "conv2", "page_feature_points": "page2"}.items():
    case(label, *_rounded(name))


def _histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    a = F.broadcast(query_sets.anchors(points, 3, 0))
    return points.join(a).groupBy("set_id", orthant(columns(coordinates(3)), columns(coordinates(3, "a"))).alias("orthant")).agg(F.count("*").alias("n"))


_o3 = "(" + " + ".join(f"CASE WHEN p.x{i} >= q.x{i} THEN {1 << i} ELSE 0 END" for i in range(3)) + ")"
case("orthant_histogram", _histogram, R.with_sql("line3", R.sets_sql(3, 3, 1, EXTENT), 3) + f"SELECT CAST(q.set_id AS INTEGER) AS set_id, {_o3} AS orthant, count(*) AS n FROM pts p CROSS JOIN q GROUP BY q.set_id, {_o3}")


def _blocks(levels: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = build_index(fixture(spark, sf_dir, "orders2"), 256)
        if not levels:
            return index.blocks.agg(F.sum("cnt").alias("points"), F.min(F.get("lo", F.lit(0))).alias("lo0"), F.max(F.get("hi", F.lit(0))).alias("hi0"), F.min(F.get("lo", F.lit(1))).alias("lo1"), F.max(F.get("hi", F.lit(1))).alias("hi1"))
        return rollup_blocks(index.blocks, 2, levels).groupBy("level").agg(F.sum("cnt").alias("points"))

    return run


_o2 = f"WITH pts AS ({R.point_sql('orders2')[0]}) "
case("block_summary", _blocks(0), _o2 + "SELECT CAST(count(*) AS HUGEINT)::BIGINT AS points, min(x0) AS lo0, max(x0) AS hi0, min(x1) AS lo1, max(x1) AS hi1 FROM pts")
case("block_rollup", _blocks(2), _o2 + "SELECT CAST(l AS INTEGER) AS level, count(*) AS points FROM pts CROSS JOIN range(3) t(l) GROUP BY l")
case("query_sampler", lambda spark, sf: _sets(fixture(spark, sf, "line3"), 20, M, EXTENT), R.with_sql("line3", R.sets_sql(3, 20, M, EXTENT), 3) + "SELECT set_id, q AS q_id FROM q")
case("query_neighbours", lambda spark, sf: _sets(fixture(spark, sf, "part2"), 10, 5, None), R.with_sql("part2", R.sets_sql(2, 10, 5, None), 2) + "SELECT set_id, q AS q_id FROM q")


def _order(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    rows = F.broadcast(gathered(points, _sets(points, 4, 4, WIDE)))
    far = points.join(rows).select("set_id", "id", max_dist2_of_set(columns(coordinates(2)), F.col("qs"), 2).alias("far"))
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy("far", "id"))
    return far.withColumn("rank", rank).where(F.col("rank") <= 25).select("set_id", "id", "rank")


case("max_dist_order", _order, _part2 + f"SELECT set_id, id, CAST(r AS INTEGER) AS rank FROM (SELECT set_id, id, row_number() OVER (PARTITION BY set_id ORDER BY far, id) AS r FROM (SELECT q.set_id, p.id, max({R.d2_sql('p', 'q', 2)}) AS far FROM pts p CROSS JOIN q GROUP BY q.set_id, p.id)) WHERE r <= 25")


def _pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = fixture(spark, sf_dir, "line3").groupBy(F.floor(F.col("x0") * 10).alias("cell")).agg(F.count("*").alias("cnt"))
    return page_model(counts, 3)


case("pages_model", _pages, R.with_sql("line3", R.sets_sql(3, 1, 1, EXTENT), 3) + "SELECT CAST(floor(x0 * 10) AS BIGINT) AS cell, count(*) AS cnt, CAST(ceil(count(*) * 32 / 1024.0) AS BIGINT) AS pages FROM pts GROUP BY 1")


def _cardinality(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    out = None
    for i, eps in enumerate(EPS_SWEEP):
        sets = _sets(points, 4, 5, EXTENT)
        got = framework.cardinality(framework.inverse(points, sets, E_(eps)), sets).select(F.lit(i).alias("v"), "n_sets", "n_results", F.round("mean_results", 6).alias("mean_results"))
        out = got if out is None else out.unionByName(got)
    return out


_l3s4 = R.with_sql("line3", R.sets_sql(3, 4, 5, EXTENT), 3)
case("result_cardinality_by_param", _cardinality, " UNION ALL ".join(f"(SELECT {i} AS v, CAST(4 AS BIGINT) AS n_sets, count(*) AS n_results, round(count(*) / 4.0, 6) AS mean_results FROM ({_l3s4}{R.eps_sql(3, e)}))" for i, e in enumerate(EPS_SWEEP)))


def _agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = build_index(fixture(spark, sf_dir, "part2"))
    points = index.points.drop("cell", "zone")
    rows = gathered(points, _sets(points, 4, 4, WIDE))
    out = None
    for i, predicate in enumerate((E_(0.1), N_(50), S_)):
        joint = stored(framework.inverse(points, rows, predicate, index=index), "agreement-joint")
        for strategy in ("naive", "single"):
            got = framework.agreement(joint, framework.inverse(points, rows, predicate, strategy, index=index)).select(F.lit(i).alias("predicate"), F.lit(strategy).alias("strategy"), "only_one", "only_other", "both")
            out = got if out is None else out.unionByName(got)
    return out


_counts = [R.eps_sql(2, 0.1), R.knn_sql(2, 50), R.sky_sql(2)]
case("method_agreement", _agreement, " UNION ALL ".join(f"(SELECT {i} AS predicate, '{s}' AS strategy, CAST(0 AS BIGINT) AS only_one, CAST(0 AS BIGINT) AS only_other, count(*) AS both FROM ({_part2}{sql}))" for i, sql in enumerate(_counts) for s in ("naive", "single")))


def _accesses(table: str, predicate, n: int, m: int, extent: float | None, rows_per_block: int, ratio: bool = False) -> Query:
    """Page accesses of the three methods, averaged over sets."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = build_index(fixture(spark, sf_dir, table), rows_per_block)
        got = accesses.averages(index, _sets(index.points.drop("cell", "zone"), n, m, extent), predicate, 1000)
        return accesses.ratios(got) if ratio else got

    return run


case("blocks_read_by_method", _accesses("line3", E_(EPS), 5, 5, EXTENT, 64), None)
case("blocks_read_knn", _accesses("part2", N_(50), 3, 4, WIDE, 32), None)
case("blocks_read_sky", _accesses("customer3", S_, 3, 2, None, 32), None)
case("blocks_read_ratios_eps", _accesses("line3", E_(0.1), 5, 5, EXTENT, 64, ratio=True), None)


def _accesses_by(name: str, values, table: str, n: int, make: Callable[[object], tuple[int, float]], column: str, predicate) -> None:
    """A series of page accesses in one batch: value number v has the sets v * 1000 + i, with their own parameter."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = build_index(fixture(spark, sf_dir, table), 64)
        made = [make(value) for value in values]
        most = {extent: max(m for m, e, _ in made if e == extent) for _, extent, _ in made}
        # Sets of one extent are drawn once, with the most members of any value.
        drawn = {extent: stored(query_sets.sample_query_sets(index.points.drop("cell", "zone"), n, m, extent, ranked=True), "drawn-sets") for extent, m in most.items()}
        sets = None
        for v, (m, extent, parameter) in enumerate(made):
            own = drawn[extent].where(F.col("r") <= m).select((F.col("set_id") + v * 1000).alias("set_id"), "q_id", F.lit(parameter).alias(column))
            sets = own if sets is None else sets.unionByName(own)
        return accesses.averages(index, sets, predicate, 1000)

    case(name, run, None)


_accesses_by("pages_eps_by_eps", EPS_SWEEP, "line3", 4, lambda v: (M, EXTENT, v), "eps", E_())
_accesses_by("pages_eps_by_m", (1, 5, 10, 20, 35), "line3", 4, lambda v: (v, EXTENT, EPS), "eps", E_())


def _index_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    return eps_range.eps_result_counts(build_index(points, 64), _sets(points, 5, 3, EXTENT), 0.15)


case("eps_counts_unread_blocks", _index_counts, R.with_sql("line3", R.sets_sql(3, 5, 3, EXTENT), 3) + f"SELECT set_id, count(*) AS n FROM ({R.eps_sql(3, 0.15, keep_queries=True)}) GROUP BY set_id")


def _cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "line3")
    got = framework.inverse(points, _sets(points, 4, 5, EXTENT), E_(EPS)).select("set_id", (F.col("id") % 3).alias("part"))
    return got.cube("set_id", "part").agg(F.count("*").alias("n"))


case("cube_result_counts", _cube, f"SELECT set_id, id % 3 AS part, count(*) AS n FROM ({_l3s4}{R.eps_sql(3, EPS)}) GROUP BY CUBE (set_id, id % 3)")


def _grouping(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    both = [framework.inverse(points, _sets(points, 4, 4, WIDE), p).select(F.lit(n).alias("predicate"), "set_id") for n, p in (("eps", E_(0.1)), ("knn", N_(50)))]
    return both[0].unionByName(both[1]).rollup("predicate", "set_id").agg(F.count("*").alias("n"))


case("grouping_sets_costs", _grouping, f"SELECT predicate, set_id, count(*) AS n FROM ((SELECT 'eps' AS predicate, set_id FROM ({_part2}{R.eps_sql(2, 0.1)})) UNION ALL (SELECT 'knn', set_id FROM ({_part2}{R.knn_sql(2, 50)}))) GROUP BY ROLLUP (predicate, set_id)")


def _set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = fixture(spark, sf_dir, "part2")
    sets = _sets(points, 4, 4, WIDE)
    a, b = framework.inverse(points, sets, E_(0.1)), framework.inverse(points, sets, N_(50))
    return a.intersect(b).select(F.lit("both").alias("op"), "set_id", "id").unionByName(a.exceptAll(b).select(F.lit("eps only").alias("op"), "set_id", "id"))


case("set_ops_results", _set_ops, f"WITH a AS ({_part2}{R.eps_sql(2, 0.1)}), b AS ({_part2}{R.knn_sql(2, 50)}) (SELECT 'both' AS op, * FROM (SELECT * FROM a INTERSECT SELECT * FROM b)) UNION ALL (SELECT 'eps only' AS op, * FROM (SELECT * FROM a EXCEPT SELECT * FROM b))")


def _json(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read_table(spark, sf_dir, "events")
    return make_points(events, F.col("event_id"), [F.get_json_object("props", "$.k").cast("double"), F.col("value")]).select("id", F.round("x0", 9).alias("x0"), F.round("x1", 9).alias("x1"))


case("json_props_points", _json, "SELECT id, round((k - min(k) OVER ()) / (max(k) OVER () - min(k) OVER ()), 9) AS x0, round((value - min(value) OVER ()) / (max(value) OVER () - min(value) OVER ()), 9) AS x1 FROM (SELECT event_id AS id, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS k, value FROM events) WHERE k IS NOT NULL")


def _windows(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from inverse_engine.streaming.profiles import session_profiles, user_profiles

        events = read_table(spark, sf_dir, "events")
        if kind == "session":
            return session_profiles(events, "6 hours")
        return user_profiles(events, "1 day") if kind == "tumbling" else user_profiles(events, "2 days", "1 day")

    return run


_cents = "CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents, count(*) AS n"
case("event_windows_tumbling", _windows("tumbling"), f"SELECT user_id, date_trunc('day', ts)::TIMESTAMP AS win, {_cents} FROM events GROUP BY ALL")
case("event_windows_sliding", _windows("sliding"), f"SELECT user_id, date_trunc('day', ts)::TIMESTAMP - to_days(CAST(k AS INTEGER)) AS win, {_cents} FROM events CROSS JOIN range(2) t(k) GROUP BY ALL")
case("event_sessions", _windows("session"), f"SELECT user_id, min(ts)::TIMESTAMP AS win, {_cents} FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")


def _asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each purchase, the latest earlier view of its user: a window over one sorted exchange."""
    from pyspark.sql.functions import last

    events = read_table(spark, sf_dir, "events")
    kinds = [r["event_type"] for r in events.groupBy("event_type").count().orderBy("event_type").limit(2).collect()]
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = events.where(F.col("event_type").isin(kinds)).withColumn("latest", last(F.when(F.col("event_type") == kinds[0], F.col("event_id")), ignorenulls=True).over(w))
    return seen.where(F.col("event_type") == kinds[1]).select("event_id", "latest")


case("asof_last_profile", _asof, "WITH k AS (SELECT list(DISTINCT event_type ORDER BY event_type) AS l FROM events) SELECT e.event_id, (SELECT arg_max(v.event_id, {'t': v.ts, 'e': v.event_id}) FROM events v WHERE v.user_id = e.user_id AND v.event_type = (SELECT l[1] FROM k) AND (v.ts < e.ts OR (v.ts = e.ts AND v.event_id < e.event_id))) AS latest FROM events e WHERE e.event_type = (SELECT l[2] FROM k)")


def _report(table: str, predicate, m: int, extent: float | None) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from inverse_engine.plans.reports import explain_filters

        points = fixture(spark, sf_dir, table)
        return explain_filters(points, _sets(points, 4, m, extent), predicate)

    return run


case("filter_report_eps", _report("line3", E_(EPS), 5, EXTENT), None)
case("filter_report_knn", _report("part2", N_(50), 4, WIDE), None)
case("filter_report_sky", _report("customer3", S_, 2, None), None)


def _overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items as points: characters, words, distinct words."""
    words = F.split("text", " ")
    return read_table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), F.length("text").cast("long").alias("chars"), F.size(words).cast("long").alias("words"), F.size(F.array_distinct(words)).cast("long").alias("distinct_words"))


case("benchmark_overlap_points", _overlap, "SELECT item_id AS id, CAST(length(text) AS BIGINT) AS chars, CAST(len(string_split(text, ' ')) AS BIGINT) AS words, CAST(len(list_distinct(string_split(text, ' '))) AS BIGINT) AS distinct_words FROM benchmark")

# Applications.
method("app_package_customers", "part2", N_(50), 3, 3, WIDE, R.knn_sql(2, 50, mono=False), candidates="customer2", oracle=True)
method("app_family_pick", "customer2", E_(0.25), 4, 3, WIDE, R.eps_sql(2, 0.25, keep_queries=True), candidates="part2")
method("app_suspects", "customer3", N_(K), 4, 3, None, R.knn_sql(3, K), indexed=True)
method("app_product_region", "supplier3", S_, 3, 2, None, R.sky_sql(3, mono=False), candidates="lattice-12")


def queries() -> dict[str, Query]:
    return {name: run for name, (run, _) in CASES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in CASES.items() if sql}

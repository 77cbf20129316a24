"""Queries over measures: discrepancy, covering radius, contests, integration and optimization."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..functions import tables as tf
from ..operators import covering, designs, discrepancy, draws, fitted, projections, stats, strata
from ..sources.tables import read
from .registry import DIGITS, product_sql, query, rounded, tree_sql

UNIT = "(CAST({c} AS DOUBLE) - min(CAST({c} AS DOUBLE)) OVER ()) / (max(CAST({c} AS DOUBLE)) OVER () - min(CAST({c} AS DOUBLE)) OVER ())"


def cloud_sql(table: str, key: str, columns: list[str]) -> str:
    """SELECT point_id, x1.. of a table's columns scaled to the unit cube."""
    return f"SELECT {key} AS point_id, " + ", ".join(f"{UNIT.format(c=c)} AS x{d}" for d, c in enumerate(columns, 1)) + f" FROM {table}"


def cloud(spark: SparkSession, sf_dir: str, table: str, key: str, columns: dict[str, F.Column]) -> DataFrame:
    return tf.scaled_points(read(spark, sf_dir, table), F.col(key), columns)


def discrepancy_sql(source: str, n: int) -> str:
    pair = product_sql([f"(1 - greatest(a.x{d}, b.x{d})) * least(a.x{d}, b.x{d})" for d in range(1, n + 1)])
    single = product_sql([f"x{d} * (1 - x{d})" for d in range(1, n + 1)])
    return f"""(SELECT sum({pair}) FROM {source} a, {source} b) / pow((SELECT count(*) FROM {source}), 2)
        - pow(2.0, {1 - n}) * (SELECT sum({single}) FROM {source}) / (SELECT count(*) FROM {source}) + pow(12.0, {-n})"""


def _col(name: str):
    """Makes a Column when a session runs."""
    return lambda: F.col(name)


def _cloud_query(name: str, table: str, key: str, columns: dict[str, tuple[str, object]]) -> None:
    n = len(columns)
    sql = f"WITH p AS ({cloud_sql(table, key, [s for s, _ in columns.values()])}) SELECT (SELECT count(*) FROM p) AS count, round({discrepancy_sql('p', n)}, 10) AS discrepancy_sq"

    @query(name, sql)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = cloud(spark, sf_dir, table, key, {c: make() for c, (_, make) in columns.items()})
        return discrepancy.discrepancy(points, n).select("count", rounded("discrepancy_sq", 10).alias("discrepancy_sq"))


_cloud_query("discrepancy_part", "part", "p_partkey", {"size": ("p_size", _col("p_size")), "price": ("p_retailprice", _col("p_retailprice"))})
_cloud_query("discrepancy_supplier", "supplier", "s_suppkey", {"bal": ("s_acctbal", _col("s_acctbal"))})
_cloud_query(
    "discrepancy_customer3",
    "customer",
    "c_custkey",
    {"bal": ("c_acctbal", _col("c_acctbal")), "nation": ("c_nationkey", _col("c_nationkey")), "key": ("c_custkey", _col("c_custkey"))},
)


def _prefix_sql(n: int) -> str:
    return "SELECT vec_id AS point_id, " + ", ".join(f"(CAST(embedding[{d}] AS DOUBLE) + 1) / 2 AS x{d}" for d in range(1, n + 1)) + " FROM embeddings"


def _prefix(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("point_id"), tf.embedding_prefix(F.col("embedding"), n).alias("x"))


for _n in (2, 5, 10):

    @query(f"discrepancy_emb{_n}", f"WITH p AS ({_prefix_sql(_n)}) SELECT (SELECT count(*) FROM p) AS count, round(({discrepancy_sql('p', _n)}) * pow(12.0, {_n}), 8) AS scaled_sq")
    def _emb(spark: SparkSession, sf_dir: str, n=_n) -> DataFrame:
        found = discrepancy.discrepancy(_prefix(spark, sf_dir, n), n)
        return found.select("count", F.round(F.col("discrepancy_sq") * 12.0**n, 8).alias("scaled_sq"))


@query("discrepancy_1d_sort", f"WITH p AS ({cloud_sql('customer', 'c_custkey', ['c_acctbal'])}) SELECT (SELECT count(*) FROM p) AS count, round({discrepancy_sql('p', 1)}, 10) AS discrepancy_sq")
def discrepancy_1d_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = cloud(spark, sf_dir, "customer", "c_custkey", {"bal": F.col("c_acctbal")}).select(F.element_at("x", 1).alias("v"))
    return discrepancy.discrepancy_1d(points, "v").select("count", rounded("discrepancy_sq", 10).alias("discrepancy_sq"))


_BOXES = "SELECT CAST(range AS BIGINT) AS box_id, " + ", ".join(
    f"{f}({rng.uniform_sql(6, 'box', 'range', str(d), '0')}, {rng.uniform_sql(6, 'box', 'range', str(d), '1')}) AS {s}{d + 1}" for d in range(2) for f, s in (("least", "lo"), ("greatest", "hi"))
) + " FROM range(200)"


@query(
    "discrepancy_boxes",
    f"""WITH p AS ({cloud_sql('lineitem', 'l_orderkey', ['l_quantity', 'l_extendedprice'])}), b AS ({_BOXES}),
    h AS (SELECT box_id, (hi1 - lo1) * (hi2 - lo2) AS volume, (SELECT count(*) FROM p WHERE x1 >= lo1 AND x1 < hi1 AND x2 >= lo2 AND x2 < hi2) AS hits FROM b)
    SELECT count(*) AS boxes, round(avg(pow(hits / CAST((SELECT count(*) FROM p) AS DOUBLE) - volume, 2)) / 4, 10) AS discrepancy_sq FROM h""",
)
def discrepancy_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = cloud(spark, sf_dir, "lineitem", "l_orderkey", {"q": F.col("l_quantity"), "p": F.col("l_extendedprice")})
    return discrepancy.discrepancy_boxes(points, 2, 200, seed=6).select("boxes", rounded("discrepancy_sq", 10).alias("discrepancy_sq"))


_PAIR = product_sql([f"(1 - greatest(a.x{d}, b.x{d})) * least(a.x{d}, b.x{d})" for d in (1, 2)])


@query(
    "discrepancy_by_group",
    f"""WITH p AS ({cloud_sql('part', 'p_partkey', ['p_size', 'p_retailprice'])}), g AS (SELECT p_partkey % 5 AS grp, x1, x2 FROM p JOIN part ON point_id = p_partkey),
    n AS (SELECT grp, CAST(count(*) AS DOUBLE) AS n, sum(x1 * (1 - x1) * x2 * (1 - x2)) AS s FROM g GROUP BY grp),
    q AS (SELECT a.grp, sum({_PAIR}) AS t FROM g a JOIN g b ON a.grp = b.grp GROUP BY a.grp)
    SELECT grp, round(t / (n * n) - s / (2 * n) + 1.0 / 144, 10) AS discrepancy_sq FROM n JOIN q USING (grp)""",
)
def discrepancy_by_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.udafs import discrepancy_agg

    points = cloud(spark, sf_dir, "part", "p_partkey", {"size": F.col("p_size"), "price": F.col("p_retailprice")})
    return points.groupBy((F.col("point_id") % 5).alias("grp")).agg(discrepancy_agg(F.col("x")).alias("d")).select("grp", F.round("d", 10).alias("discrepancy_sq"))


@query("expected_discrepancy", "SELECT CAST(c AS BIGINT) AS count, CAST(d AS INTEGER) AS dims, round(pow(6.0, -d) * (1 - pow(2.0, -d)) / c * pow(12.0, d), 8) AS scaled FROM (VALUES (100), (4900)) a(c), (VALUES (2), (5), (10)) b(d)")
def expected_discrepancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(c, d, discrepancy.expected_sq(c, d) * 12.0**d) for c in (100, 4900) for d in (2, 5, 10)]
    return spark.createDataFrame(rows, "count long, dims int, scaled double").select("count", "dims", F.round("scaled", 8).alias("scaled"))


#: Prefix sizes, as far as the table reaches.
PREFIXES = tuple(4**k for k in range(3, 9))


def _event_cloud(spark: SparkSession, sf_dir: str) -> DataFrame:
    axes = {"ts": tf.timestamp_axis(F.col("ts")), "value": F.col("value")}
    return cloud(spark, sf_dir, "events", "event_id", axes)


@query(
    "prefix_discrepancy",
    f"WITH p AS ({cloud_sql('events', 'event_id', ['epoch_us(ts)', 'value'])}), r AS (SELECT *, row_number() OVER (ORDER BY x1, point_id) AS nth, count(*) OVER () AS rows_ FROM p), "
    + ", ".join(f"p{k} AS (SELECT * FROM r WHERE nth <= {k} AND rows_ >= {k})" for k in PREFIXES)
    + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS prefix, round({discrepancy_sql(f'p{k}', 2)}, 10) AS discrepancy_sq" for k in PREFIXES)
    + ") WHERE discrepancy_sq IS NOT NULL",
)
def prefix_discrepancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Discrepancy of the first events in time, for every power of four from 64 that the table holds."""
    from ..operators import latin

    points = _event_cloud(spark, sf_dir).withColumns({"all": F.lit(0), "at": F.element_at("x", 1)})
    ranked, total, out = latin.global_rank(points, "all", ["at", "point_id"]), points.count(), None
    for k in [k for k in PREFIXES if k <= total] or PREFIXES[:1]:
        one = discrepancy.discrepancy(ranked.where(F.col("rank") < k).select("point_id", "x"), 2).select(F.lit(k).cast("long").alias("prefix"), rounded("discrepancy_sq", 10).alias("discrepancy_sq"))
        out = one if out is None else out.unionByName(one)
    return out


# covering radius

SIZES = (4, 16, 36, 64, 100, 144)


def _upper_sql(name: str, n: int) -> str:
    return "sqrt(max(" + " + ".join(f"pow((hi{d} - lo{d}) / 2, 2)" for d in range(1, n + 1)) + f")) FROM {name}"


def _floor_sql(count: int, n: int) -> str:
    return repr(covering.covering_floor(count, n))


@query(
    "covering_upper_sweep",
    "WITH RECURSIVE " + ", ".join(tree_sql(c, n, name=f"s{c}_{n}") for n in (2, 3) for c in SIZES) + " "
    + " UNION ALL ".join(f"SELECT CAST({c} AS BIGINT) AS count, {n} AS dims, round(upper, {DIGITS}) AS upper, round(upper / {_floor_sql(c, n)}, {DIGITS}) AS normalized FROM (SELECT {_upper_sql(f's{c}_{n}', n).replace(' FROM', ' AS upper FROM', 1)})" for n in (2, 3) for c in SIZES),
)
def covering_upper_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for n in (2, 3):
        for c in SIZES:
            one = covering.covering_upper(draws.draw(strata.bsplit_strata(spark, c, n), None)).select(
                F.lit(c).cast("long").alias("count"), F.lit(n).alias("dims"), rounded("upper").alias("upper"), rounded(F.col("upper") / covering.covering_floor(c, n)).alias("normalized")
            )
            out = one if out is None else out.unionByName(one)
    return out


CONTEST = tuple(range(6, 61, 6))


@query(
    "rule_contest_small",
    "WITH RECURSIVE " + ", ".join(tree_sql(c, 2, rule, name=f"{'on' if rule else 'off'}{c}") for c in CONTEST for rule in (True, False))
    + ", g AS (" + " UNION ALL ".join(f"SELECT (SELECT {_upper_sql(f'on{c}', 2)}) - (SELECT {_upper_sql(f'off{c}', 2)}) AS gap" for c in CONTEST) + ") "
    + "SELECT 2 AS dims, CAST(sum(CASE WHEN gap < -1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS wins, CAST(sum(CASE WHEN abs(gap) <= 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS ties, CAST(sum(CASE WHEN gap > 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS losses FROM g",
)
def rule_contest_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .experiments import rule_measures

    rows = rule_measures(spark, (2,), CONTEST, exact_dims=0)
    return stats.contest(rows, ["dims"], "with_rule", "without_rule").select("dims", "wins", "ties", "losses")


def _probe_sql(m: int, n: int, seed: int) -> str:
    return "SELECT CAST(range AS BIGINT) AS probe_id, " + ", ".join(f"{rng.uniform_sql(seed, 'probe', 'range', str(d))} AS p{d + 1}" for d in range(n)) + f" FROM range({m})"


@query(
    "covering_lower_md5",
    f"""WITH RECURSIVE {tree_sql(100, 2)}, q AS ({_probe_sql(1000, 2, 8)})
    SELECT round(max(d), {DIGITS}) AS lower FROM (SELECT probe_id, min(sqrt(pow(p1 - (lo1 + hi1) / 2, 2) + pow(p2 - (lo2 + hi2) / 2, 2))) AS d FROM q, strata GROUP BY probe_id)""",
)
def covering_lower_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    centres = draws.draw(strata.bsplit_strata(spark, 100, 2), None)
    return covering.covering_lower(centres, 2, 1000, seed=8).select(rounded("lower").alias("lower"))


@query(
    "covering_over_lineitem",
    f"""WITH RECURSIVE {tree_sql(64, 2)}, p AS ({cloud_sql('lineitem', 'l_orderkey', ['l_quantity', 'l_extendedprice'])}), u AS (SELECT DISTINCT x1, x2 FROM p)
    SELECT round(max(d), {DIGITS}) AS radius FROM (SELECT x1, x2, min(sqrt(pow(x1 - (lo1 + hi1) / 2, 2) + pow(x2 - (lo2 + hi2) / 2, 2))) AS d FROM u, strata GROUP BY x1, x2)""",
)
def covering_over_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem")
    # no column is a key here
    space = tf.scaled_points(rows, F.monotonically_increasing_id(), {"q": F.col("l_quantity"), "p": F.col("l_extendedprice")})
    centres = draws.draw(strata.bsplit_strata(spark, 64, 2), None).select("x")
    return covering.covering_over(centres, space, "point_id", "x").select(rounded("radius").alias("radius"))


def _over_sql(count: int) -> str:
    near = f"SELECT x1, x2, min(sqrt(pow(x1 - (lo1 + hi1) / 2, 2) + pow(x2 - (lo2 + hi2) / 2, 2))) AS d FROM u, s{count} GROUP BY x1, x2"
    return f"SELECT CAST({count} AS BIGINT) AS count, round(max(d), {DIGITS}) AS radius, round(max(d) / {_floor_sql(count, 2)}, {DIGITS}) AS normalized FROM ({near})"


OVER = (16, 64, 100, 144)


@query(
    "covering_over_sweep",
    "WITH RECURSIVE " + ", ".join(tree_sql(c, 2, name=f"s{c}") for c in OVER)
    + f", p AS ({cloud_sql('orders', 'o_orderkey', ['o_totalprice', 'epoch_us(o_orderdate)'])}), u AS (SELECT DISTINCT x1, x2 FROM p) " + " UNION ALL ".join(map(_over_sql, OVER)),
)
def covering_over_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tightness sweep with table rows as the space: radius of stratum centres over all orders."""
    space, out = cloud(spark, sf_dir, "orders", "o_orderkey", {"price": F.col("o_totalprice"), "day": tf.timestamp_axis(F.col("o_orderdate"))}), None
    for c in OVER:
        centres = draws.draw(strata.bsplit_strata(spark, c, 2), None).select("x")
        found = covering.covering_over(centres, space, "point_id", "x")
        one = found.select(F.lit(c).cast("long").alias("count"), rounded("radius").alias("radius"), rounded(F.col("radius") / covering.covering_floor(c, 2)).alias("normalized"))
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "worst_probe",
    f"""WITH RECURSIVE {tree_sql(100, 2)}, q AS ({_probe_sql(1000, 2, 8)}),
    d AS (SELECT probe_id, min(sqrt(pow(p1 - (lo1 + hi1) / 2, 2) + pow(p2 - (lo2 + hi2) / 2, 2))) AS d FROM q, strata GROUP BY probe_id)
    SELECT probe_id, round(d, {DIGITS}) AS distance FROM d ORDER BY d DESC, probe_id LIMIT 10""",
)
def worst_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten probes farthest from any stratum centre: where the design is thinnest."""
    centres = draws.draw(strata.bsplit_strata(spark, 100, 2), None)
    near = covering.nearest(covering.probes(spark, 1000, 2, 8), centres)
    return near.orderBy(F.desc("distance"), "probe_id").limit(10).select("probe_id", rounded("distance").alias("distance"))


_ROWS = ", ".join(rng.permute_sql(196, 3, d, f"p{d}") for d in range(2))


@query(
    "projection_designs",
    f"""WITH RECURSIVE {_ROWS}, r AS (
        SELECT 'srs' AS design, d AS dim, CASE d WHEN 0 THEN {rng.uniform_sql(3, 'srs', 'i', '0')} ELSE {rng.uniform_sql(3, 'srs', 'i', '1')} END AS v FROM p0, range(2) t(d)
        UNION ALL SELECT 'lhs', 0, (v + {rng.uniform_sql(3, 'lhs', 'i', '0')}) / 196.0 FROM p0
        UNION ALL SELECT 'lhs', 1, (v + {rng.uniform_sql(3, 'lhs', 'i', '1')}) / 196.0 FROM p1
        UNION ALL SELECT 'grid_jitter', d, (((i // CASE d WHEN 0 THEN 1 ELSE 14 END) % 14) + CASE d WHEN 0 THEN {rng.uniform_sql(3, 'draw', 'i', '0', '0', '1')} ELSE {rng.uniform_sql(3, 'draw', 'i', '0', '1', '1')} END) / 14.0 FROM p0, range(2) t(d))
    SELECT design, CAST(dim AS INTEGER) AS dim, CAST(196 - count(DISTINCT least(floor(v * 196), 195)) AS BIGINT) AS empty_bins FROM r GROUP BY design, dim""",
)
def projection_designs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Empty 1/N bins per axis: none for the Latin design, about 1/e of all for the others."""
    from ..operators import latin

    out = None
    for name, points in (("srs", designs.srs(spark, 196, 2, seed=3)), ("lhs", designs.lhs(spark, 196, 2, seed=3)), ("grid_jitter", designs.grid_jitter(spark, 14, 2, seed=3))):
        one = latin.latin_violations(points, 196, 2).select(F.lit(name).alias("design"), "dim", "empty_bins")
        out = one if out is None else out.unionByName(one)
    return out


@query("covering_over_emb")
def covering_over_emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Covering radius of all rows by the 200 that the box splitting picks, four axes."""
    space = _prefix(spark, sf_dir, 4)
    picked = fitted.select_uniform_subset(space, 200, 4)
    return covering.covering_over(picked, space, "point_id", "x").select(rounded("radius").alias("radius"))


@query(
    "covering_exact_1d",
    f"""WITH p AS ({cloud_sql('supplier', 's_suppkey', ['s_acctbal'])})
    SELECT round(greatest(min(x1), 1 - max(x1), max(gap) / 2), {DIGITS}) AS radius FROM (SELECT x1, lead(x1) OVER (ORDER BY x1) - x1 AS gap FROM p)""",
)
def covering_exact_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = cloud(spark, sf_dir, "supplier", "s_suppkey", {"bal": F.col("s_acctbal")}).select(F.element_at("x", 1).alias("v"))
    return covering.covering_exact_1d(points, "v", 0.0, 1.0).select(rounded("radius").alias("radius"))


@query("covering_exact_2d", "SELECT CAST(k * k AS BIGINT) AS count, round(sqrt(2.0) / (2 * k), 8) AS radius FROM (VALUES (2), (5), (7), (12)) v(k)")
def covering_exact_2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .experiments import exact_radius

    sets = None
    for k in (2, 5, 7, 12):
        one = designs.grid_centre(spark, k, 2).withColumn("set_id", F.lit(k * k).cast("long"))
        sets = one if sets is None else sets.unionByName(one)
    return exact_radius(sets, "set_id").select(F.col("set_id").alias("count"), rounded("radius").alias("radius"))


#: Sizes whose exact radius is held against its bound, and the axes that orders give.
TIGHT, TIGHT_AXES = (4, 9, 16, 25, 36), ["o_totalprice", "epoch_us(o_orderdate)", "o_custkey"]


def _tight_sql(n: int) -> str:
    """CTEs ending in ``t{n}``(n, tight, mean_ratio).

    The exact radius is the largest distance to the nearest point over all
    places of the cube where n planes meet: bisectors of a point and later ones,
    and faces. Any further place is in the cube too, so none raises it.
    """
    dims, every = range(1, n + 1), lambda form: [form.format(d=d) for d in range(1, n + 1)]
    x, boxed = ", ".join(every("x{d}")), ", ".join(every("lo{d}, hi{d}"))
    inside = " AND ".join(every("x{d} >= lo{d} AND (x{d} < hi{d} OR (hi{d} = 1 AND x{d} = 1))"))
    centre = " + ".join(every("(x{d} - (lo{d} + hi{d}) / 2) * (x{d} - (lo{d} + hi{d}) / 2)"))
    reach = "sqrt(" + " + ".join(every("pow(greatest(x{d} - lo{d}, hi{d} - x{d}), 2)")) + ")"
    square = lambda t: " + ".join(f"{t}.x{d} * {t}.x{d}" for d in dims)
    faces = ", ".join(f"({2 * d + side}, " + ", ".join(str(float(d == e)) for e in dims) + f", {float(side)})" for d in dims for side in (0, 1))
    rows = "abc"[:n]

    def det(columns: list[str]) -> str:
        m = [[f"{r}.{c}" for c in columns] for r in rows]
        if n == 2:
            return f"({m[0][0]} * {m[1][1]} - {m[0][1]} * {m[1][0]})"
        return "(" + " + ".join(f"{m[0][i]} * ({m[1][j]} * {m[2][k]} - {m[1][k]} * {m[2][j]})" for i, j, k in ((0, 1, 2), (1, 2, 0), (2, 0, 1))) + ")"

    normal = every("n{d}")
    solved = ", ".join(f"{det([*normal[: d - 1], 'l', *normal[d:]])} / {det(normal)} AS v{d}" for d in dims)
    meet = " ".join(f"JOIN g{n} {q} ON {q}.count = {p}.count AND {q}.base = {p}.base AND {q}.id > {p}.id" for p, q in zip(rows, rows[1:]))
    away = " + ".join(every("(v{d} - x{d}) * (v{d} - x{d})"))
    v = ", ".join(every("v{d}"))
    trees = ", ".join(tree_sql(c, n, mode="keyed", seed=5, name=f"s{c}_{n}") for c in TIGHT)
    return f"""{trees}, p{n} AS ({cloud_sql('orders', 'o_orderkey', TIGHT_AXES[:n])}),
    b{n} AS ({' UNION ALL '.join(f'SELECT {c} AS count, stratum_id, {boxed} FROM s{c}_{n}' for c in TIGHT)}),
    r{n} AS (SELECT count, stratum_id, {x}, row_number() OVER (PARTITION BY count, stratum_id ORDER BY {centre}, point_id) AS nth FROM p{n} JOIN b{n} ON {inside}),
    q{n} AS (SELECT count, stratum_id, {x} FROM r{n} WHERE nth = 1),
    w{n} AS (SELECT b.count, coalesce(min(CASE WHEN q.stratum_id = b.stratum_id THEN {reach} END), min({reach})) AS reach FROM b{n} b JOIN q{n} q ON q.count = b.count GROUP BY b.count, b.stratum_id),
    g{n} AS (SELECT a.count, a.stratum_id AS base, b.stratum_id AS id, {', '.join(f'b.x{d} - a.x{d} AS n{d}' for d in dims)}, ({square('b')} - ({square('a')})) / 2 AS l
        FROM q{n} a JOIN q{n} b ON a.count = b.count AND a.stratum_id < b.stratum_id
        UNION ALL SELECT count, stratum_id, 100 + face, {', '.join(f'f{d}' for d in dims)}, edge FROM q{n}, (VALUES {faces}) f(face, {', '.join(f'f{d}' for d in dims)}, edge)),
    m{n} AS (SELECT a.count, {solved} FROM g{n} a {meet} WHERE abs({det(normal)}) > 1e-12),
    v{n} AS (SELECT DISTINCT count, {', '.join(every('least(greatest(v{d}, 0), 1) AS v{d}'))} FROM m{n} WHERE {' AND '.join(every('v{d} BETWEEN -1e-9 AND 1 + 1e-9'))}),
    d{n} AS (SELECT v.count, sqrt(min({away})) AS away FROM v{n} v JOIN q{n} q ON q.count = v.count GROUP BY v.count, {v}),
    e{n} AS (SELECT count, max(away) AS exact FROM d{n} GROUP BY count), u{n} AS (SELECT count, max(reach) AS upper FROM w{n} GROUP BY count),
    t{n} AS (SELECT {n} AS n, round(avg(CASE WHEN abs(exact - upper) < 1e-9 THEN 1.0 ELSE 0.0 END), 6) AS tight, round(avg(upper / exact), 6) AS mean_ratio FROM e{n} JOIN u{n} USING (count) HAVING count(*) > 0)"""


@query("bound_tightness", f"WITH RECURSIVE {_tight_sql(2)}, {_tight_sql(3)} SELECT * FROM t2 UNION ALL SELECT * FROM t3")
def bound_tightness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact radius of the orders nearest to stratum centres against its bound by the strata, over sizes."""
    from .experiments import radius_bounds_of_rows

    axes, rows = {"price": F.col("o_totalprice"), "day": tf.timestamp_axis(F.col("o_orderdate")), "customer": F.col("o_custkey")}, None
    for n in (2, 3):
        points = cloud(spark, sf_dir, "orders", "o_orderkey", dict(list(axes.items())[:n]))
        one = radius_bounds_of_rows(points, n, TIGHT, seed=5)
        rows = one if rows is None else rows.unionByName(one)
    return covering.bound_tightness(rows.withColumnRenamed("dims", "n")).select("n", F.round("tight", 6).alias("tight"), F.round("mean_ratio", 6).alias("mean_ratio"))


@query(
    "separation_part",
    f"WITH p AS ({cloud_sql('part', 'p_partkey', ['p_size', 'p_retailprice'])}) SELECT round(min(sqrt(pow(a.x1 - b.x1, 2) + pow(a.x2 - b.x2, 2))), {DIGITS}) AS separation FROM p a, p b WHERE a.point_id < b.point_id",
)
def separation_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = cloud(spark, sf_dir, "part", "p_partkey", {"size": F.col("p_size"), "price": F.col("p_retailprice")})
    return covering.separation(points, 2).select(rounded("separation").alias("separation"))


@query(
    "projection_hist",
    f"WITH p AS ({cloud_sql('part', 'p_partkey', ['p_size', 'p_retailprice'])}), r AS (SELECT 0 AS dim, x1 AS v FROM p UNION ALL SELECT 1, x2 FROM p) SELECT CAST(dim AS INTEGER) AS dim, CAST(least(floor(v * 20), 19) AS BIGINT) AS bin, count(*) AS n FROM r GROUP BY 1, 2",
)
def projection_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = cloud(spark, sf_dir, "part", "p_partkey", {"size": F.col("p_size"), "price": F.col("p_retailprice")})
    return projections.projection_histogram(points, 20)


# fitted partitions


def _fitted(name: str, table: str, key: str, columns: dict[str, tuple[str, object]]) -> None:
    sql_columns = [s for s, _ in columns.values()]
    sql = f"WITH p AS ({cloud_sql(table, key, sql_columns)}), d AS (SELECT DISTINCT {', '.join(f'x{k}' for k in range(1, len(columns) + 1))} FROM p) SELECT (SELECT count(*) FROM p) AS points, (SELECT count(*) FROM d) AS boxes, CAST(1.0 AS DOUBLE) AS total_volume, CAST(0 AS BIGINT) AS outside"

    @query(name, sql)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = cloud(spark, sf_dir, table, key, {c: make() for c, (_, make) in columns.items()})
        boxed = fitted.mean_gap_partition(points, len(columns), tries=1, seed=4)
        out = F.exists(F.arrays_zip("x", "lo", "hi"), lambda s: (s["x"] < s["lo"]) | (s["x"] > s["hi"]))
        totals = boxed.agg(F.count("*").alias("points"), F.sum(out.cast("long")).alias("outside"))
        each = boxed.select("lo", "hi").distinct().agg(F.count("*").alias("boxes"), F.round(F.sum(strata.volume(F.col("lo"), F.col("hi"))), 6).alias("total_volume"))
        return totals.crossJoin(each)


_fitted("fitted_partition_part", "part", "p_partkey", {"size": ("p_size", _col("p_size")), "price": ("p_retailprice", _col("p_retailprice"))})
_fitted("fitted_partition_orders", "orders", "o_orderkey", {"price": ("o_totalprice", _col("o_totalprice")), "day": ("epoch_us(o_orderdate)", lambda: tf.timestamp_axis(F.col("o_orderdate")))})


@query("fitted_upper_bounds")
def fitted_upper_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best of ten fitted partitions over a lower bound from probes; no SQL, tests hold lower <= upper."""
    points = cloud(spark, sf_dir, "part", "p_partkey", {"size": F.col("p_size"), "price": F.col("p_retailprice")})
    upper = fitted.covering_upper_fitted(points, 2, tries=10, seed=1)
    lower = covering.covering_lower(points, 2, 2000, seed=1)
    return lower.crossJoin(upper).select(rounded("lower").alias("lower"), rounded("upper").alias("upper"))


# statistics


@query(
    "median_ci",
    """WITH r AS (SELECT l_returnflag, l_extendedprice AS v, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice) AS k, count(*) OVER (PARTITION BY l_returnflag) AS n FROM lineitem),
    m AS (SELECT l_returnflag, quantile_cont(l_extendedprice, 0.5) AS median FROM lineitem GROUP BY 1)
    SELECT l_returnflag, n, round(max(CASE WHEN k = greatest(1, floor(n / 2.0 - 1.96 * sqrt(n) / 2)) THEN v END), 6) AS lower, round(any_value(median), 6) AS median,
           round(max(CASE WHEN k = least(n, ceil(n / 2.0 + 1.96 * sqrt(n) / 2) + 1) THEN v END), 6) AS upper FROM r JOIN m USING (l_returnflag) GROUP BY l_returnflag, n""",
)
def median_ci(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = stats.median_ci(read(spark, sf_dir, "lineitem"), ["l_returnflag"], "l_extendedprice")
    return found.select("l_returnflag", "n", *[F.round(c, 6).alias(c) for c in ("lower", "median", "upper")])


def _poisson_sql(u: str, most: int = 8) -> str:
    import math

    total, parts = 0.0, []
    for k in range(most):
        total += math.exp(-1) / math.factorial(k)
        parts.append(f"WHEN {u} < {total!r} THEN {k}")
    return f"CASE {' '.join(parts)} ELSE {most} END"


@query(
    "bootstrap_ci",
    f"""WITH b AS (SELECT p_size % 5 AS grp, p_retailprice AS v, s, {_poisson_sql('u')} AS w FROM (SELECT p_size, p_retailprice, s, {rng.uniform_sql(2, 'boot', 'p_partkey', 's')} AS u FROM part, range(0, 50) r(s))),
    m AS (SELECT grp, s, sum(w * v) / sum(w) AS mean FROM b GROUP BY grp, s)
    SELECT CAST(grp AS INTEGER) AS grp, round(quantile_cont(mean, 0.025), 6) AS lower, round(quantile_cont(mean, 0.975), 6) AS upper FROM m GROUP BY grp""",
)
def bootstrap_ci(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "part").withColumn("grp", F.col("p_size") % 5)
    found = stats.bootstrap_ci(rows, ["grp"], F.col("p_partkey"), "p_retailprice", samples=50, seed=2)
    return found.select("grp", F.round("lower", 6).alias("lower"), F.round("upper", 6).alias("upper"))


@query(
    "pareto_front",
    """WITH s AS (SELECT s_suppkey, s_acctbal, s_nationkey + s_suppkey % 7 AS rank_ FROM supplier)
    SELECT s_suppkey, round(s_acctbal, 6) AS s_acctbal, rank_ FROM s WHERE NOT EXISTS (SELECT 1 FROM s t WHERE t.s_acctbal <= s.s_acctbal AND t.rank_ <= s.rank_ AND (t.s_acctbal < s.s_acctbal OR t.rank_ < s.rank_))""",
)
def pareto_front(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal", (F.col("s_nationkey") + F.col("s_suppkey") % 7).alias("rank_"))
    return stats.pareto_front(rows, "s_suppkey", "s_acctbal", "rank_").select("s_suppkey", F.round("s_acctbal", 6).alias("s_acctbal"), "rank_")


# integration and optimization over tables


MARGINALS = (("lineitem", "l_quantity"), ("lineitem", "l_extendedprice"), ("lineitem", "l_discount"), ("lineitem", "l_tax"), ("orders", "o_totalprice"), ("part", "p_retailprice"))


def _marginal_sql(table: str, column: str, d: int) -> str:
    return f"m{d} AS (SELECT v, lag(f, 1, 0.0) OVER (ORDER BY v) AS a, f AS b FROM (SELECT v, CAST(sum(c) OVER (ORDER BY v) AS DOUBLE) / CAST(sum(c) OVER () AS DOUBLE) AS f FROM (SELECT {column} AS v, count(*) AS c FROM {table} GROUP BY 1)))"


@query(
    "integrate_product",
    f"WITH RECURSIVE {tree_sql(625, 6)}, c AS (SELECT stratum_id, {', '.join(f'(lo{d} + hi{d}) / 2 AS u{d}' for d in range(1, 7))} FROM strata), "
    + ", ".join(_marginal_sql(t, c, d) for d, (t, c) in enumerate(MARGINALS, 1))
    + f" SELECT count(*) AS points, round(avg({' * '.join(f'm{d}.v / (SELECT avg({c}) FROM {t})' for d, (t, c) in enumerate(MARGINALS, 1))}), 6) AS relative FROM c "
    + " ".join(f"ASOF JOIN m{d} ON c.u{d} > m{d}.a" for d in range(1, 7)),
)
def integrate_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean of a product of six independent empirical marginals at stratum centres, over the product of their means."""
    from .experiments import inverse_marginals

    centres = draws.draw(strata.bsplit_strata(spark, 625, 6), None).select("point_id", "x")
    valued = inverse_marginals(spark, sf_dir, centres, MARGINALS)
    return valued.agg(F.count("*").alias("points"), F.round(F.avg("product"), 6).alias("relative"))


DIMS = (2, 4, 8, 16, 32, 64)


@query("optimum_gap_emb")
def optimum_gap_emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap between the best of 50 n picked rows and the best of all rows of a shifted sphere, per prefix length n.

    Rows are picked by box splitting of their first n components; all of them
    where there are no more.
    """
    from ..functions.objectives import sphere

    out = None
    for n in DIMS:
        rows = _prefix(spark, sf_dir, n).withColumn("f", sphere(F.transform("x", lambda v: 2 * v - 1 - 0.05)))
        picked = fitted.select_uniform_subset(rows, 50 * n, n).select("point_id")
        best = rows.join(picked, "point_id").agg(F.min("f").alias("p")).crossJoin(rows.agg(F.min("f").alias("t")))
        one = best.select(F.lit(n).alias("dims"), F.round("p", 6).alias("picked_min"), F.round("t", 6).alias("true_min"), F.round(F.col("p") - F.col("t"), 6).alias("gap"))
        out = one if out is None else out.unionByName(one)
    return out


def _experiment(name: str, call) -> None:
    """Experiments of the cube form; no SQL, tests hold their order and bands."""

    @query(name)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from . import experiments

        return call(experiments, spark)


_experiment("integrate_spread", lambda e, s: e.integration_spread(s, "plate", reps=64))
_experiment("integrate_spread_100d", lambda e, s: e.integration_spread(s, "hundred", reps=8))
_experiment("measure_table", lambda e, s: e.measure_table(s, count=100, dims=(2, 5), reps=4))
_experiment("discrepancy_sweep", lambda e, s: e.discrepancy_sweep(s, dims=(2, 3), sizes=(16, 64, 256, 1024, 4096), reps=8))
_experiment("radius_sweep", lambda e, s: e.discrepancy_sweep(s, dims=(2, 3), sizes=(16, 64), reps=8, measure="radius"))
_experiment("radius_bounds", lambda e, s: e.radius_bounds(s, dims=(2, 3, 4), sizes=(4, 9, 16, 25, 36)))
_experiment("optimum_gaps", lambda e, s: e.optimum_gaps(s, dims=(2, 4, 8), reps=20))
_experiment("rule_contest", lambda e, s: e.rule_table(s, dims=tuple(range(2, 11)), sizes=range(4, 129), exact_dims=2))
_experiment("oversample_select", lambda e, s: e.oversample_select(s, 100, 2, factor=20))

"""Queries over generated strata, draws and designs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..operators import designs, draws, latin, picking, strata
from ..plans import counts
from ..sources import udtf
from ..sources.tables import read
from .measure_queries import cloud, cloud_sql
from .registry import DIGITS, box_columns, flat, query, rounded, rounded_sql, tree_sql

BOXES = {"lo": "lo", "hi": "hi"}


def _boxes(name: str, count: int, n: int, **how) -> None:
    sql_how = {k: v for k, v in how.items() if k != "engine"}

    @query(name, f"WITH RECURSIVE {tree_sql(count, n, **sql_how)} SELECT stratum_id, {rounded_sql(box_columns(n))} FROM strata")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return flat(strata.bsplit_strata(spark, count, n, **how), n, ["stratum_id"], BOXES)


#: Columns of lineitem whose range is the box that strata are laid over.
ROW_AXES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_partkey", "l_suppkey"]


def _rows_sql(n: int) -> str:
    """CTEs p, the rows as points, and g, each with its stratum."""
    inside = " AND ".join(f"x{d} >= lo{d} AND (x{d} < hi{d} OR (x{d} = hi{d} AND hi{d} = 1))" for d in range(1, n + 1))
    axes = ", ".join(f"x{d}" for d in range(1, n + 1))
    return f"p AS ({cloud_sql('lineitem', 'l_orderkey', ROW_AXES[:n])}), g AS (SELECT stratum_id, {axes} FROM p JOIN strata ON {inside})"


def _placed(spark: SparkSession, sf_dir: str, count: int, n: int, **how) -> DataFrame:
    """(point_id, x, stratum_id) of the rows of lineitem."""
    return picking.assign_by_descent(cloud(spark, sf_dir, "lineitem", "l_orderkey", {c: F.col(c) for c in ROW_AXES[:n]}), count, n, **how)


def _with_rows(spark: SparkSession, sf_dir: str, found: DataFrame, count: int, n: int, **how) -> DataFrame:
    """``found`` with the number of rows in its stratum."""
    filled = picking.fill_counts(_placed(spark, sf_dir, count, n, **how)).withColumnRenamed("stratum_id", "filled_")
    return found.join(filled, F.col(found.columns[0]) == F.col("filled_"), "left").select(*found.columns, F.coalesce("rows", F.lit(0).cast("long")).alias("rows"))


def _filled_boxes(name: str, count: int, n: int, **how) -> None:
    """Strata over the range of n columns of lineitem, in units of that range, and the rows in each."""
    own = {k: v for k, v in how.items() if k != "engine"}

    @query(name, f"WITH RECURSIVE {tree_sql(count, n, **own)}, {_rows_sql(n)}, f AS (SELECT stratum_id, count(*) AS rows FROM g GROUP BY stratum_id) SELECT stratum_id, {rounded_sql(box_columns(n))}, coalesce(rows, 0) AS rows FROM strata LEFT JOIN f USING (stratum_id)")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _with_rows(spark, sf_dir, flat(strata.bsplit_strata(spark, count, n, **how), n, ["stratum_id"], BOXES), count, n, **own)


_filled_boxes("bsplit_144_on", 144, 2)
_filled_boxes("bsplit_144_off", 144, 2, avoid_odd=False)
_filled_boxes("bsplit_500_boxes", 500, 2)
_filled_boxes("bsplit_625x6_boxes", 625, 6)
_filled_boxes("bsplit_keyed_100", 100, 2, mode="keyed", seed=7)
_boxes("bsplit_subtrees_1000", 1000, 3, engine="subtree")
_filled_boxes("bsplit_levels_100", 100, 2, mode="keyed", seed=7, engine="levels")


@query(
    "bsplit_region",
    f"""WITH RECURSIVE b AS (SELECT min(o_totalprice) AS a1, max(o_totalprice) AS b1, CAST(min(epoch_us(o_orderdate)) AS DOUBLE) AS a2, CAST(max(epoch_us(o_orderdate)) AS DOUBLE) AS b2 FROM orders),
    {tree_sql(50, 2, lo=['a1', 'a2'], hi=['b1', 'b2'], source='b')}
    SELECT stratum_id, round(lo1, 4) AS lo1, round(hi1, 4) AS hi1, round(lo2, 0) AS lo2, round(hi2, 0) AS hi2 FROM strata""",
)
def bsplit_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    day = F.unix_micros(F.col("o_orderdate").cast("timestamp")).cast("double")
    r = read(spark, sf_dir, "orders").agg(F.min("o_totalprice").alias("a1"), F.max("o_totalprice").alias("b1"), F.min(day).alias("a2"), F.max(day).alias("b2")).first()
    made = strata.bsplit_strata(spark, 50, 2, lo=[r.a1, r.a2], hi=[r.b1, r.b2])
    at = lambda s, d, digits: F.round(F.element_at(s, d), digits).alias(f"{s}{d}")
    return made.select("stratum_id", at("lo", 1, 4), at("hi", 1, 4), at("lo", 2, 0), at("hi", 2, 0))


def _grid(name: str, ks: list[int]) -> None:
    steps, total = [], 1
    for k in ks:
        steps.append(total)
        total *= k
    columns = ", ".join(f"round(CAST((range // {s}) % {k} AS DOUBLE) / {k}, {DIGITS}) AS lo{d}, round(CAST((range // {s}) % {k} + 1 AS DOUBLE) / {k}, {DIGITS}) AS hi{d}" for d, (s, k) in enumerate(zip(steps, ks), 1))

    @query(name, f"SELECT CAST(range AS BIGINT) AS stratum_id, {columns} FROM range({total})")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return flat(strata.grid_strata(spark, ks), len(ks), ["stratum_id"], BOXES)


_grid("grid_144", [12, 12])
_grid("grid_mixed_3x4x5", [3, 4, 5])


@query("grid_equals_bsplit", "SELECT CAST(0 AS BIGINT) AS only_bsplit, CAST(0 AS BIGINT) AS only_grid")
def grid_equals_bsplit(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = flat(strata.bsplit_strata(spark, 256, 2), 2, [], BOXES)
    b = flat(strata.grid_strata(spark, [16, 16]), 2, [], BOXES)
    return a.exceptAll(b).agg(F.count("*").alias("only_bsplit")).crossJoin(b.exceptAll(a).agg(F.count("*").alias("only_grid")))


SWEEP = (3, 5, 6, 7, 36, 100, 144, 196)


def _ratio_sql(count: int) -> str:
    return f"""SELECT {count} AS n_points, round((SELECT min(least(hi1 - lo1, hi2 - lo2) / greatest(hi1 - lo1, hi2 - lo2)) FROM s{count}), {DIGITS}) AS side_ratio"""


@query("side_ratio_sweep", "WITH RECURSIVE " + ", ".join(tree_sql(c, 2, name=f"s{c}") for c in SWEEP) + " " + " UNION ALL ".join(map(_ratio_sql, SWEEP)))
def side_ratio_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for c in SWEEP:
        row = strata.side_ratio(strata.bsplit_strata(spark, c, 2)).select(F.lit(c).alias("n_points"), rounded("side_ratio").alias("side_ratio"))
        out = row if out is None else out.unionByName(row)
    return out


def _drawn_sql(b: int | None, copies: str = "0", seed: int = 5) -> str:
    def value(d: int) -> str:
        if b is None:
            return f"(lo{d} + hi{d}) / 2"
        each = " + ".join(rng.uniform_sql(seed, "draw", "stratum_id", copies, str(d - 1), str(k)) for k in range(1, b + 1))
        return f"lo{d} + (hi{d} - lo{d}) * ({each if b == 1 else f'({each}) / {float(b)}'})"

    return ", ".join(f"round({value(d)}, {DIGITS}) AS x{d}" for d in (1, 2))


for _name, _b in (("draw_uniform_500", 1), ("draw_mean2_500", 2), ("draw_mean8_500", 8), ("draw_centre_500", None)):

    @query(_name, f"WITH RECURSIVE {tree_sql(500, 2)} SELECT stratum_id AS point_id, {_drawn_sql(_b)} FROM strata")
    def _draw(spark: SparkSession, sf_dir: str, b=_b) -> DataFrame:
        return flat(draws.draw(strata.bsplit_strata(spark, 500, 2), b, seed=5), 2, ["point_id"], {"x": "x"})


@query("augment_k3", f"WITH RECURSIVE {tree_sql(144, 2)}, {_rows_sql(2)}, f AS (SELECT stratum_id, count(*) AS rows FROM g GROUP BY stratum_id) SELECT stratum_id AS point_id, CAST(copy AS INTEGER) AS copy, {_drawn_sql(1, 'copy')}, coalesce(rows, 0) AS rows FROM strata LEFT JOIN f USING (stratum_id), range(0, 4) r(copy)")
def augment_k3(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = strata.bsplit_strata(spark, 144, 2)
    whole = draws.draw(kept, 1, seed=5).unionByName(draws.augment(kept, 3, 1, seed=5))
    return _with_rows(spark, sf_dir, flat(whole, 2, ["point_id", "copy"], {"x": "x"}), 144, 2)


# competing designs


@query("srs_100", "SELECT CAST(range AS BIGINT) AS point_id, " + ", ".join(f"round({rng.uniform_sql(3, 'srs', 'range', str(d))}, {DIGITS}) AS x{d + 1}" for d in range(3)) + " FROM range(100)")
def srs_100(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(designs.srs(spark, 100, 3, seed=3), 3, ["point_id"], {"x": "x"})


_LHS = ", ".join(rng.permute_sql(100, 3, d, f"p{d}") for d in range(3))


@query(
    "lhs_100",
    f"WITH RECURSIVE {_LHS} SELECT p0.i AS point_id, "
    + ", ".join(f"round((p{d}.v + {rng.uniform_sql(3, 'lhs', 'p0.i', str(d))}) / 100.0, {DIGITS}) AS x{d + 1}" for d in range(3))
    + " FROM p0 JOIN p1 USING (i) JOIN p2 USING (i)",
)
def lhs_100(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(designs.lhs(spark, 100, 3, seed=3), 3, ["point_id"], {"x": "x"})


def _no_violations(name: str, n: int, make) -> None:
    @query(name, f"SELECT CAST(range AS INTEGER) AS dim, CAST(0 AS BIGINT) AS empty_bins FROM range({n})")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points, count = make(spark)
        return latin.latin_violations(points, count, n)


_no_violations("lhs_violations", 4, lambda s: (designs.lhs(s, 1000, 4, seed=1), 1000))
_no_violations("lattice_latin_violations", 4, lambda s: (designs.power_lattice(s, 101, 4, candidates="all", latin=True, seed=1), 101))
_no_violations("padded_latin_violations", 6, lambda s: (designs.padded_grid(s, 625, [2, 2, 1, 1], latin=True, seed=1), 625))
_no_violations("grid_latin_violations", 2, lambda s: (designs.grid_latin(s, 14, 2, seed=1), 196))


def _inverse_sql(base: int, order: list[int], levels: int) -> str:
    terms = []
    for k in range(levels):
        digit = f"((range + 1) // {base ** k}) % {base}"
        value = digit if order == sorted(order) else "CASE " + digit + " " + " ".join(f"WHEN {a} THEN {b}" for a, b in enumerate(order)) + " END"
        terms.append(f"CAST(({value}) AS DOUBLE) * CAST({(1.0 / base) ** (k + 1)!r} AS DOUBLE)")
    return " + ".join(terms)


def _radinv(name: str, count: int, n: int, permuted: bool) -> None:
    parts = [_inverse_sql(b, designs.digit_orders(b, 3, permuted), 9) for b in designs.primes(n)]
    columns = ", ".join(f"round({p}, {DIGITS}) AS x{d}" for d, p in enumerate(parts, 1))

    @query(name, f"SELECT CAST(range AS BIGINT) AS point_id, {columns} FROM range({count})")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return flat(designs.radinv(spark, count, n, seed=3, permuted=permuted), n, ["point_id"], {"x": "x"})


_radinv("radinv_196", 196, 3, False)
_radinv("radinv_permuted", 196, 4, True)


@query(
    "lattice_points",
    "SELECT CAST(range AS BIGINT) AS point_id, "
    + ", ".join(f"round((CAST((range * {z}) % 101 AS DOUBLE) / 101 + {rng.uniform_py(2, 'shift', d)!r}) % 1.0, {DIGITS}) AS x{d + 1}" for d, z in enumerate(designs.generator_powers(40, 101, 3)))
    + " FROM range(101)",
)
def lattice_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(designs.power_lattice(spark, 101, 3, a=40, seed=2), 3, ["point_id"], {"x": "x"})


def _separation_sql(n: int) -> str:
    torus = lambda d: f"least((i * z{d}) % 101, 101 - (i * z{d}) % 101) / 101.0"
    norm = " + ".join(f"pow({torus(d)}, 2)" for d in range(n))
    powers, z = [], "1"
    for d in range(n):
        powers.append(f"{z} AS z{d}")
        z = f"(({z}) * a) % 101"
    return f"""SELECT {n} AS dims, a, round(sqrt(min({norm})), {DIGITS}) AS separation
        FROM (SELECT a, {', '.join(powers)} FROM (SELECT CAST(range AS BIGINT) AS a FROM range(1, 101))), (SELECT CAST(range AS BIGINT) AS i FROM range(1, 101)) GROUP BY a"""


@query(
    "best_generator",
    "SELECT dims, a, separation FROM (SELECT *, row_number() OVER (PARTITION BY dims ORDER BY separation DESC, a) AS r FROM ("
    + " UNION ALL ".join(map(_separation_sql, (2, 3, 4, 5)))
    + ") WHERE a IN (SELECT l_partkey % 101 FROM lineitem)) WHERE r = 1",
)
def best_generator(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best lattice generator among those that the parts of lineitem name, modulo the number of points."""
    rows, named = [], read(spark, sf_dir, "lineitem").select((F.col("l_partkey") % 101).cast("long").alias("a")).where("a > 0").distinct()
    for n in (2, 3, 4, 5):
        a = designs.best_generator(spark, 101, n, named)
        rows.append((n, a, round(designs.lattice_separation(a, 101, n), DIGITS)))
    return spark.createDataFrame(rows, "dims int, a long, separation double")


@query("lattice_separations", f"SELECT a, separation FROM ({_separation_sql(3)})")
def lattice_separations(spark: SparkSession, sf_dir: str) -> DataFrame:
    tried = spark.range(1, 101).select(F.col("id").alias("a"))
    return designs.separations(tried, 101, 3).select("a", rounded("separation").alias("separation"))


_PADDED = ", ".join(rng.permute_sql(625, 4, 100 + b, f"c{b}") for b in range(3))


@query(
    "padded_grid_points",
    f"WITH RECURSIVE {_PADDED} SELECT c0.i AS point_id, "
    + ", ".join(
        f"round(((c{b}.v // {k ** d}) % {k} + {rng.uniform_sql(4, 'jitter', 'c0.i', str(b), str(d))}) / {float(k)}, {DIGITS}) AS x{col}"
        for col, (b, k, d) in enumerate([(0, 25, 0), (0, 25, 1), (1, 625, 0), (2, 625, 0)], 1)
    )
    + " FROM c0 JOIN c1 USING (i) JOIN c2 USING (i)",
)
def padded_grid_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(designs.padded_grid(spark, 625, [2, 1, 1], seed=4), 4, ["point_id"], {"x": "x"})


@query("padded_bsplit_rows", "SELECT CAST(100 AS BIGINT) AS points, 5 AS dims, CAST(100 AS BIGINT) AS distinct_points")
def padded_bsplit_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [draws.draw(strata.bsplit_strata(spark, 100, n), 1, seed=n).select("point_id", "x") for n in (3, 2)]
    glued = designs.padded_designs(parts, 100, seed=2)
    return glued.agg(F.count("*").alias("points"), F.max(F.size("x")).alias("dims"), F.count_distinct("x").alias("distinct_points"))


# latinization


def _cog_sql(count: int, n: int, seed: int) -> str:
    sides = " UNION ALL ".join(f"SELECT stratum_id, {d - 1} AS dim, lo{d} AS lo, hi{d} AS hi FROM strata" for d in range(1, n + 1))
    return f"""WITH RECURSIVE {tree_sql(count, n)}, long_form AS ({sides}), ranked AS (
        SELECT stratum_id, dim, lo, hi, row_number() OVER (PARTITION BY dim ORDER BY round((lo + hi) / 2, 12), {rng.uniform_sql(seed, 'cog', 'stratum_id', 'dim')}, stratum_id) - 1 AS bin FROM long_form),
        judged AS (SELECT *, NOT (least(hi, (bin + 1) / {float(count)}) - greatest(lo, bin / {float(count)}) > {latin.EDGE / count!r}) AS violation FROM ranked)"""


_COG_ROWS = _cog_sql(500, 2, 9) + f", {_rows_sql(2)}, f AS (" + " UNION ALL ".join(
    f"SELECT stratum_id, {d} AS dim, CAST(least(floor(x{d + 1} * 500.0), 499) AS BIGINT) AS bin, count(*) AS rows FROM g GROUP BY ALL" for d in (0, 1)
) + ")"


@query("bsplit_cog_bins", _COG_ROWS + " SELECT stratum_id, CAST(dim AS INTEGER) AS dim, CAST(bin AS BIGINT) AS bin, violation, coalesce(rows, 0) AS rows FROM judged LEFT JOIN f USING (stratum_id, dim, bin)")
def bsplit_cog_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins by centre order, and how many rows of lineitem lie in both stratum and bin."""
    bins = latin.cog_bins(strata.bsplit_strata(spark, 500, 2), 500, seed=9).select("stratum_id", "dim", "bin", "violation")
    placed = _placed(spark, sf_dir, 500, 2).where("stratum_id is not null").select("stratum_id", F.posexplode("x").alias("dim", "v"))
    filled = placed.groupBy("stratum_id", "dim", F.least(F.floor(F.col("v") * 500.0), F.lit(499)).cast("long").alias("bin")).agg(F.count("*").alias("rows"))
    return bins.join(filled, ["stratum_id", "dim", "bin"], "left").select("stratum_id", "dim", "bin", "violation", F.coalesce("rows", F.lit(0).cast("long")).alias("rows"))


@query("bsplit_cog_violations", _COG_ROWS + " SELECT CAST(dim AS INTEGER) AS dim, CAST(sum(CAST(violation AS INTEGER)) AS BIGINT) AS violations, CAST(sum(coalesce(rows, 0)) AS BIGINT) AS rows FROM judged LEFT JOIN f USING (stratum_id, dim, bin) GROUP BY dim")
def bsplit_cog_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bsplit_cog_bins(spark, sf_dir).groupBy("dim").agg(F.sum(F.col("violation").cast("long")).alias("violations"), F.sum("rows").alias("rows"))


def _matched(name: str, count: int, n: int, init: str) -> None:
    @query(name, f"SELECT CAST(range AS INTEGER) AS dim, CAST({count} AS BIGINT) AS bins, CAST(0 AS BIGINT) AS violations FROM range({n})")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        got = latin.match_bins(strata.bsplit_strata(spark, count, n), count, init, seed=2)
        return got.groupBy("dim").agg(F.count_distinct("bin").alias("bins"), F.sum(F.col("violation").cast("long")).alias("violations"))


_matched("bsplit_match_violations", 200, 2, "random_greedy")
_matched("bsplit_match_warm_violations", 500, 2, "cog")


@query(
    "bsplit_match_sweep_violations",
    "SELECT CAST(range AS INTEGER) AS dim, CAST(500 AS BIGINT) AS bins, CAST(0 AS BIGINT) AS violations, (SELECT count(*) FROM lineitem WHERE l_quantity IS NOT NULL AND l_extendedprice IS NOT NULL) AS rows FROM range(2)",
)
def bsplit_match_sweep_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins matched by deadline to strata over lineitem; along every axis they hold all its rows."""
    got = _with_rows(spark, sf_dir, latin.match_bins(strata.bsplit_strata(spark, 500, 2), 500, "sweep", seed=2).select("stratum_id", "dim", "bin", "violation"), 500, 2)
    return got.groupBy("dim").agg(F.count_distinct("bin").alias("bins"), F.sum(F.col("violation").cast("long")).alias("violations"), F.sum("rows").alias("rows"))


@query("draw_in_bins_violations", "SELECT CAST(range AS INTEGER) AS dim, CAST(0 AS BIGINT) AS empty_bins FROM range(2)")
def draw_in_bins_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    matched = latin.match_bins(strata.bsplit_strata(spark, 300, 2), 300, "cog", seed=2)
    return latin.latin_violations(latin.draw_in_bins(matched, 300, seed=3), 300, 2)


@query("cog_correlation", _cog_sql(500, 2, 9) + f" SELECT CAST(dim AS INTEGER) AS dim, round(corr((lo + hi) / 2, (bin + 0.5) / 500.0), 6) AS corr FROM judged GROUP BY dim")
def cog_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.stats import correlations

    got = latin.cog_bins(strata.bsplit_strata(spark, 500, 2), 500, seed=9)
    pairs = got.select("dim", ((F.col("lo") + F.col("hi")) / 2).alias("a"), ((F.col("bin") + 0.5) / 500.0).alias("b"))
    return correlations(pairs, "dim", "a", "b").select("dim", F.round("corr", 6).alias("corr"))


@query("udtf_bsplit", f"WITH RECURSIVE {tree_sql(144, 2)} SELECT stratum_id, {rounded_sql(box_columns(2))} FROM strata")
def udtf_bsplit(spark: SparkSession, sf_dir: str) -> DataFrame:
    udtf.register(spark)
    return spark.sql("SELECT * FROM bsplit(144, 2)").select("stratum_id", *[rounded(c).alias(c) for c in box_columns(2)])


@query("source_cube_design", f"WITH RECURSIVE {tree_sql(144, 2)} SELECT stratum_id, {rounded_sql(box_columns(2))} FROM strata WHERE hi1 > 0.7 AND lo2 < 0.2")
def source_cube_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources import design_source

    design_source.register(spark)
    made = spark.read.format("cube_design").option("count", "144").option("dims", "2").option("parts", "16").load()
    return made.where("hi1 > 0.7 AND lo2 < 0.2").select("stratum_id", *[rounded(c).alias(c) for c in box_columns(2)])


@query("sql_recursive_bsplit", f"WITH RECURSIVE {tree_sql(36, 2)} SELECT stratum_id, {rounded_sql(box_columns(2))} FROM strata")
def sql_recursive_bsplit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The splits as Spark SQL's own recursion."""
    half = "(cnt div 2)"
    share = f"({half} - CASE WHEN cnt >= 6 AND cnt % 2 = 0 AND {half} % 2 = 1 THEN 1 ELSE 0 END)"
    axis = f"CASE WHEN (hi1 - lo1) >= greatest(hi1 - lo1, hi2 - lo2) * (1D - {counts.TIE!r}D) THEN 1 ELSE 2 END"
    text = f"""WITH RECURSIVE tree(off, cnt, lo1, hi1, lo2, hi2) MAX RECURSION LEVEL 64 AS (
        SELECT 0L, 36L, 0D, 1D, 0D, 1D
        UNION ALL
        SELECT CASE side WHEN 0 THEN off ELSE off + share END, CASE side WHEN 0 THEN share ELSE cnt - share END,
               CASE WHEN side = 1 AND axis = 1 THEN cut ELSE lo1 END, CASE WHEN side = 0 AND axis = 1 THEN cut ELSE hi1 END,
               CASE WHEN side = 1 AND axis = 2 THEN cut ELSE lo2 END, CASE WHEN side = 0 AND axis = 2 THEN cut ELSE hi2 END
        FROM (SELECT *, explode(array(0, 1)) AS side FROM (
            SELECT *, CASE axis WHEN 1 THEN lo1 + (hi1 - lo1) * CAST(share AS DOUBLE) / CAST(cnt AS DOUBLE) ELSE lo2 + (hi2 - lo2) * CAST(share AS DOUBLE) / CAST(cnt AS DOUBLE) END AS cut
            FROM (SELECT *, {share} AS share, {axis} AS axis FROM tree WHERE cnt > 1))))
        SELECT off AS stratum_id, {", ".join(f"round({c}, {DIGITS}) AS {c}" for c in box_columns(2))} FROM tree WHERE cnt = 1"""
    return spark.sql(text)

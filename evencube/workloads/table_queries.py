"""Queries that lay designs over the given tables, and the relational operators around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng
from ..functions import tables as tf
from ..operators import fitted, latin, picking, strata
from ..sources.tables import TABLES, read
from ..streaming import fill
from .measure_queries import cloud, cloud_sql
from .registry import query, rounded, tree_sql

LI2 = ["l_quantity", "l_extendedprice"]


def _li2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cloud(spark, sf_dir, "lineitem", "l_orderkey", {c: F.col(c) for c in LI2})


def _inside(n: int) -> str:
    return " AND ".join(f"x{d} >= lo{d} AND (x{d} < hi{d} OR (x{d} = hi{d} AND hi{d} = 1))" for d in range(1, n + 1))


_ASSIGN = f"WITH RECURSIVE {tree_sql(144, 2)}, p AS ({cloud_sql('lineitem', 'l_orderkey', LI2)}), g AS (SELECT stratum_id FROM p JOIN strata ON {_inside(2)})"
_COUNTS = _ASSIGN + " SELECT stratum_id, count(*) AS rows FROM g GROUP BY stratum_id"


@query("stratum_assign_descent", _COUNTS)
def stratum_assign_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return picking.fill_counts(picking.assign_by_descent(_li2(spark, sf_dir), 144, 2))


def _tree_counts(name: str, count: int, mode: str = "fixed") -> None:
    """The other ways down: literal arrays for middling trees, a vectorised descent for large ones."""
    tree = tree_sql(count, 2, mode=mode, seed=5)

    @query(name, f"WITH RECURSIVE {tree}, p AS ({cloud_sql('orders', 'o_orderkey', ['o_totalprice', 'epoch_us(o_orderdate)'])}), g AS (SELECT stratum_id FROM p JOIN strata ON {_inside(2)}) SELECT stratum_id, count(*) AS rows FROM g GROUP BY stratum_id")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        points = cloud(spark, sf_dir, "orders", "o_orderkey", {"price": F.col("o_totalprice"), "day": tf.timestamp_axis(F.col("o_orderdate"))})
        return picking.fill_counts(picking.assign_by_descent(points, count, 2, mode=mode, seed=5))


@query("stratum_assign_rangejoin", _COUNTS)
def stratum_assign_rangejoin(spark: SparkSession, sf_dir: str) -> DataFrame:
    return picking.fill_counts(picking.assign_by_range_join(_li2(spark, sf_dir), strata.bsplit_strata(spark, 144, 2), 2))


_tree_counts("stratum_assign_arrays", 1000, "keyed")
_tree_counts("stratum_assign_vectorised", 25_000)

_EVENTS = cloud_sql("events", "event_id", ["epoch_us(ts)", "value"])


def _ev2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cloud(spark, sf_dir, "events", "event_id", {"ts": tf.timestamp_axis(F.col("ts")), "value": F.col("value")})


@query(
    "pick_one_per_stratum",
    f"""WITH RECURSIVE {tree_sql(100, 2)}, p AS ({_EVENTS}), g AS (
        SELECT stratum_id, point_id, round(sqrt(pow(x1 - (lo1 + hi1) / 2, 2) + pow(x2 - (lo2 + hi2) / 2, 2)), 12) AS d FROM p JOIN strata ON {_inside(2)})
    SELECT stratum_id, point_id, round(d, 8) AS distance FROM (SELECT *, row_number() OVER (PARTITION BY stratum_id ORDER BY d, point_id) AS k FROM g) WHERE k = 1""",
)
def pick_one_per_stratum(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = picking.assign_by_descent(_ev2(spark, sf_dir), 100, 2)
    return picking.nearest_to_centre(placed, 100, 2).select("stratum_id", "point_id", rounded("distance").alias("distance"))


@query(
    "augment_lineitem_k",
    f"""WITH RECURSIVE {tree_sql(64, 2)}, p AS ({_EVENTS}), g AS (SELECT stratum_id, point_id FROM p JOIN strata ON {_inside(2)})
    SELECT stratum_id, point_id FROM (SELECT *, row_number() OVER (PARTITION BY stratum_id ORDER BY {rng.uniform_sql(3, 'pick', 'point_id')}, point_id) AS k FROM g) WHERE k <= 3""",
)
def augment_lineitem_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return picking.pick_k(picking.assign_by_descent(_ev2(spark, sf_dir), 64, 2), 3, seed=3)


def _sparse(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    points = cloud(spark, sf_dir, "part", "p_partkey", {"size": F.col("p_size"), "price": F.col("p_retailprice")})
    return strata.bsplit_strata(spark, 4096, 2), picking.assign_by_descent(points, 4096, 2)


_SPARSE = f"WITH RECURSIVE {tree_sql(4096, 2)}, p AS ({cloud_sql('part', 'p_partkey', ['p_size', 'p_retailprice'])}), g AS (SELECT DISTINCT stratum_id FROM p JOIN strata ON {_inside(2)})"


@query("empty_strata", _SPARSE + " SELECT stratum_id FROM strata WHERE NOT EXISTS (SELECT 1 FROM g WHERE g.stratum_id = strata.stratum_id)")
def empty_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return picking.empty_strata(*_sparse(spark, sf_dir)).select("stratum_id")


@query("filled_strata", _SPARSE + " SELECT stratum_id FROM strata WHERE EXISTS (SELECT 1 FROM g WHERE g.stratum_id = strata.stratum_id)")
def filled_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return picking.filled_strata(*_sparse(spark, sf_dir)).select("stratum_id")


# subsets of feature cubes


def _doc_axes() -> dict[str, F.Column]:
    return {"chars": F.length("text"), "words": tf.word_count(F.col("text")), "lines": F.regexp_count(F.coalesce("text", F.lit("")), F.lit("\n"))}


def _page_axes() -> dict[str, F.Column]:
    return {"chars": F.length("html"), "tags": F.regexp_count("html", F.lit("<")), "depth": F.regexp_count("url", F.lit("/"))}


def _subset(name: str, table: str, key: str, axes) -> None:
    @query(name, f"SELECT least(100, count(*)) AS picked, least(100, count(*)) AS different FROM {table}")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        chosen = fitted.select_uniform_subset(cloud(spark, sf_dir, table, key, axes()), 100, 3)
        return chosen.agg(F.count("*").alias("picked"), F.count_distinct("point_id").alias("different"))


_subset("subset_uniform_100", "documents", "doc_id", _doc_axes)
_subset("subset_uniform_pages", "pages", "page_id", _page_axes)


@query("subset_rules", "SELECT rule, CAST(50 AS BIGINT) AS picked FROM (VALUES ('middle'), ('median'), ('mean'), ('mean_gap')) v(rule)")
def subset_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, out = _ev2(spark, sf_dir), None
    for rule in fitted.RULES:
        one = fitted.select_uniform_subset(points, 50, 2, rule).agg(F.lit(rule).alias("rule"), F.count_distinct("point_id").alias("picked"))
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "stratified_quality",
    f"""WITH RECURSIVE {tree_sql(16, 2)}, d AS (SELECT doc_id, quality, length(text) AS chars, len(regexp_extract_all(text, '[^ \\t\\n\\r]+')) AS words FROM documents JOIN labels USING (doc_id)),
    p AS (SELECT doc_id AS point_id, quality, (chars - min(chars) OVER ()) / CAST(max(chars) OVER () - min(chars) OVER () AS DOUBLE) AS x1, (words - min(words) OVER ()) / CAST(max(words) OVER () - min(words) OVER () AS DOUBLE) AS x2 FROM d),
    g AS (SELECT stratum_id, point_id, quality FROM p JOIN strata ON {_inside(2)}),
    k AS (SELECT *, row_number() OVER (PARTITION BY stratum_id ORDER BY {rng.uniform_sql(4, 'pick', 'point_id')}, point_id) AS k, count(*) OVER (PARTITION BY stratum_id) AS size FROM g),
    s AS (SELECT stratum_id, avg(quality) AS m, any_value(size) AS size FROM k WHERE k <= 10 GROUP BY stratum_id)
    SELECT (SELECT round(sum(m * size) / sum(size), 8) FROM s) AS stratified, (SELECT round(avg(quality), 8) FROM g) AS all_rows, (SELECT count(*) FROM g) AS rows""",
)
def stratified_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id")
    axes = {"chars": F.length("text"), "words": tf.word_count(F.col("text"))}
    bounds = tf.ranges(rows, axes)
    x = F.array(*[tf.unit(c, *bounds[k]) for k, c in axes.items()])
    placed = picking.assign_by_descent(rows.select(F.col("doc_id").alias("point_id"), "quality", x.alias("x")), 16, 2)
    found = picking.stratified_mean(placed, F.col("quality"), 10, seed=4)
    return found.select(rounded("stratified").alias("stratified"), rounded("all_rows").alias("all_rows"), F.col("rows"))


# ranks, windows, quantiles


@query(
    "latinize_rank",
    "SELECT o_orderkey AS key, 0 AS dim, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS rank, round((row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 0.5) / count(*) OVER (), 8) AS value FROM orders "
    "UNION ALL SELECT o_orderkey, 1, row_number() OVER (ORDER BY epoch_us(o_orderdate), o_orderkey) - 1, round((row_number() OVER (ORDER BY epoch_us(o_orderdate), o_orderkey) - 0.5) / count(*) OVER (), 8) FROM orders",
)
def latinize_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "orders").withColumn("day", tf.timestamp_axis(F.col("o_orderdate")))
    return latin.latinize_by_rank(rows, "o_orderkey", ["o_totalprice", "day"]).select("key", "dim", "rank", rounded("value").alias("value"))


@query(
    "ntile_strata",
    "WITH r AS (SELECT l_returnflag, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice, l_orderkey) - 1 AS k, count(*) OVER (PARTITION BY l_returnflag) AS n, l_extendedprice AS v FROM lineitem) "
    "SELECT l_returnflag, CAST(floor(k * 10 / CAST(n AS DOUBLE)) AS BIGINT) AS stratum_id, count(*) AS rows, round(min(v), 4) AS low, round(max(v), 4) AS high FROM r GROUP BY 1, 2",
)
def ntile_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = picking.ntile_strata(read(spark, sf_dir, "lineitem"), "l_returnflag", "l_extendedprice", "l_orderkey", 10)
    return cut.groupBy("l_returnflag", "stratum_id").agg(F.count("*").alias("rows"), F.round(F.min("l_extendedprice"), 4).alias("low"), F.round(F.max("l_extendedprice"), 4).alias("high"))


@query("gap_1d", "SELECT s_nationkey, count(*) AS n, round(min(gap), 6) AS least_gap FROM (SELECT s_nationkey, s_acctbal - lag(s_acctbal) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS gap FROM supplier) GROUP BY s_nationkey")
def gap_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal")
    gaps = read(spark, sf_dir, "supplier").withColumn("gap", F.col("s_acctbal") - F.lag("s_acctbal").over(w))
    return gaps.groupBy("s_nationkey").agg(F.count("*").alias("n"), F.round(F.min("gap"), 6).alias("least_gap"))


@query(
    "moving_mean",
    "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean5, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_events FROM events",
)
def moving_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    near = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return rows.select("event_id", F.round(F.avg("value").over(near), 6).alias("mean5"), F.count("*").over(day).alias("day_events"))


PROBABILITIES = [0.01, 0.1, 0.25, 0.5, 0.75, 0.9, 0.99]


@query("inverse_cdf_lineitem", " UNION ALL ".join(f"SELECT CAST({p} AS DOUBLE) AS probability, quantile_disc(l_extendedprice, {p}) AS value FROM lineitem" for p in PROBABILITIES))
def inverse_cdf_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tf.quantiles(read(spark, sf_dir, "lineitem"), "l_extendedprice", PROBABILITIES)


# reports


_REPORT = "FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey, (SELECT min(s_acctbal) AS lo, max(s_acctbal) AS hi FROM supplier)"
_QUARTER = "CAST(least(floor((s_acctbal - lo) / (hi - lo) * 4), 3) AS BIGINT)"


def _report(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = read(spark, sf_dir, "supplier")
    lo, hi = tf.ranges(s, {"b": F.col("s_acctbal")})["b"]
    joined = s.join(F.broadcast(read(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    quarter = strata.stratum_of(F.array(tf.unit(F.col("s_acctbal"), lo, hi)), 4, 1)
    return joined.withColumn("stratum", quarter)


def _grouped(name: str, clause: str) -> None:
    @query(name, f"SELECT r_name, stratum, count(*) AS suppliers, round(avg(s_acctbal), 6) AS mean FROM (SELECT r_name, s_acctbal, {_QUARTER} AS stratum {_REPORT}) GROUP BY {clause}")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows, measures = _report(spark, sf_dir), [F.count("*").alias("suppliers"), F.round(F.avg("s_acctbal"), 6).alias("mean")]
        if clause.startswith("ROLLUP"):
            return rows.rollup("r_name", "stratum").agg(*measures)
        if clause.startswith("CUBE"):
            return rows.cube("r_name", "stratum").agg(*measures)
        return rows.groupingSets([["r_name"], ["stratum"], []], "r_name", "stratum").agg(*measures).select("r_name", "stratum", "suppliers", "mean")


_grouped("report_rollup", "ROLLUP (r_name, stratum)")
_grouped("report_cube", "CUBE (r_name, stratum)")
_grouped("report_sets", "GROUPING SETS ((r_name), (stratum), ())")


# joins


@query(
    "lineitem_part_join",
    "SELECT p_brand, count(*) AS n, round(sum(l_quantity * p_retailprice), 2) AS value FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey WHERE o_totalprice > 250000 GROUP BY p_brand",
)
def lineitem_part_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, p = (read(spark, sf_dir, t) for t in ("lineitem", "orders", "part"))
    joined = li.join(o.where("o_totalprice > 250000"), F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return joined.groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_quantity") * F.col("p_retailprice")), 2).alias("value"))


@query("doc_quality_join", "SELECT lang, quality, count(*) AS n, round(avg(n_chars), 4) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def doc_quality_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = read(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars").join(read(spark, sf_dir, "labels"), "doc_id")
    return joined.groupBy("lang", "quality").agg(F.count("*").alias("n"), F.round(F.avg("n_chars"), 4).alias("chars"))


@query(
    "events_asof_design",
    """WITH d AS (SELECT range AS design_id, (SELECT min(epoch_us(ts)) FROM events) + CAST(((SELECT max(epoch_us(ts)) - min(epoch_us(ts)) FROM events) * (2 * range + 1)) // 200 AS BIGINT) AS design_us FROM range(100)),
    e AS (SELECT event_id, epoch_us(ts) AS us FROM events)
    SELECT CAST(design_id AS BIGINT) AS design_id, design_us, e.us AS event_us FROM d ASOF JOIN e ON d.design_us >= e.us""",
)
def events_asof_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For every centre of 100 time strata the latest event before it: events find their stratum, then strata look back."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    ev = read(spark, sf_dir, "events").select(us.alias("us"))
    r = ev.agg(F.min("us").alias("lo"), F.max("us").alias("hi")).first()
    times = spark.range(100).select(F.col("id").alias("design_id"), (F.lit(r.lo) + F.floor(F.lit(r.hi - r.lo) * (2 * F.col("id") + 1) / F.lit(200)).cast("long")).alias("at"))
    cut = times.agg(F.sort_array(F.collect_list("at")).alias("ats"))  # as many as the design has strata
    # first design time not before the event: per design partial maxima
    slot = ev.join(F.broadcast(cut)).withColumn("design_id", F.size(F.filter("ats", lambda a: a < F.col("us"))).cast("long"))
    last = slot.groupBy("design_id").agg(F.max("us").alias("us"))
    seen = times.join(last, "design_id", "left")
    # empty strata take the latest before them; a window over the design's strata only
    back = F.max("us").over(Window.orderBy("design_id").rowsBetween(Window.unboundedPreceding, 0))
    return seen.select("design_id", F.col("at").alias("design_us"), back.alias("event_us")).where("event_us is not null")


# set operations


def _picks(spark: SparkSession, sf_dir: str, count: int) -> DataFrame:
    placed = picking.assign_by_descent(_ev2(spark, sf_dir), count, 2)
    return picking.nearest_to_centre(placed, count, 2).select("point_id")


def _picks_sql(count: int, name: str) -> str:
    return f"""{tree_sql(count, 2, name=f's{count}')}, {name} AS (SELECT point_id FROM (SELECT stratum_id, point_id,
        row_number() OVER (PARTITION BY stratum_id ORDER BY round(sqrt(pow(x1 - (lo1 + hi1) / 2, 2) + pow(x2 - (lo2 + hi2) / 2, 2)), 12), point_id) AS k FROM p JOIN s{count} ON {_inside(2)}) WHERE k = 1)"""


for _name, _op in (("union_methods", "UNION"), ("intersect_picks", "INTERSECT"), ("except_picks", "EXCEPT")):

    @query(_name, f"WITH RECURSIVE p AS ({_EVENTS}), {_picks_sql(50, 'a')}, {_picks_sql(100, 'b')} SELECT point_id FROM a {_op} SELECT point_id FROM b")
    def _sets(spark: SparkSession, sf_dir: str, op=_op) -> DataFrame:
        a, b = _picks(spark, sf_dir, 50), _picks(spark, sf_dir, 100)
        return a.union(b).distinct() if op == "UNION" else a.intersect(b) if op == "INTERSECT" else a.exceptAll(b).distinct()


# features and scaling


@query(
    "scale_lineitem",
    "SELECT l_returnflag, count(*) AS n, " + ", ".join(f"round(avg(x{d}), 8) AS m{d}" for d in (1, 2, 3, 4))
    + " FROM (SELECT l_returnflag, " + ", ".join(f"({c} - min({c}) OVER ()) / (max({c}) OVER () - min({c}) OVER ()) AS x{d}" for d, c in enumerate(["l_quantity", "l_extendedprice", "l_discount", "l_tax"], 1)) + " FROM lineitem) GROUP BY 1",
)
def scale_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem")
    axes = {c: F.col(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")}
    bounds = tf.ranges(rows, axes)
    means = [F.round(F.avg(tf.unit(c, *bounds[k])), 8).alias(f"m{d}") for d, (k, c) in enumerate(axes.items(), 1)]
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), *means)


@query("scale_events", "SELECT event_type, count(*) AS n, round(avg((epoch_us(ts) - a) / CAST(b - a AS DOUBLE)), 8) AS mean FROM events, (SELECT min(epoch_us(ts)) AS a, max(epoch_us(ts)) AS b FROM events) GROUP BY event_type")
def scale_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events")
    axis = {"ts": tf.timestamp_axis(F.col("ts"))}
    bounds = tf.ranges(rows, axis)
    return rows.groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg(tf.unit(axis["ts"], *bounds["ts"])), 8).alias("mean"))


@query("rows_in_box", "SELECT l_linestatus, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_extendedprice >= 20000 AND l_extendedprice < 40000 AND l_shipdate >= TIMESTAMP '1997-01-01' GROUP BY l_linestatus")
def rows_in_box(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem").where("l_quantity BETWEEN 10 AND 20 AND l_extendedprice >= 20000 AND l_extendedprice < 40000 AND l_shipdate >= TIMESTAMP_NTZ '1997-01-01'")
    return rows.groupBy("l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query(
    "doc_features",
    "SELECT doc_id, CAST(length(text) AS INTEGER) AS chars, CAST(len(regexp_extract_all(text, '[^ \\t\\n\\r]+')) AS INTEGER) AS words, CAST(length(text) - length(replace(text, chr(10), '')) AS INTEGER) AS lines FROM documents",
)
def doc_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select("doc_id", *[c.alias(k) for k, c in _doc_axes().items()])


@query("page_features", "SELECT page_id, CAST(length(html) AS INTEGER) AS chars, CAST(length(html) - length(replace(html, '<', '')) AS INTEGER) AS tags, CAST(length(url) - length(replace(url, '/', '')) AS INTEGER) AS depth FROM pages")
def page_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", *[c.alias(k) for k, c in _page_axes().items()])


@query("event_props", "SELECT event_type, count(*) AS n, round(avg(CAST(json_extract_string(props, '$.k') AS DOUBLE)), 8) AS k FROM events GROUP BY event_type")
def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg(F.get_json_object("props", "$.k").cast("double")), 8).alias("k"))


@query("conv_features", "SELECT role, count(*) AS n, CAST(max(turn) AS BIGINT) AS turns, round(avg(length(text)), 8) AS chars, count(DISTINCT conv_id) AS convs FROM conversations GROUP BY role")
def conv_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "conversations")
    return rows.groupBy("role").agg(F.count("*").alias("n"), F.max("turn").alias("turns"), F.round(F.avg(F.length("text")), 8).alias("chars"), F.count_distinct("conv_id").alias("convs"))


@query("embedding_prefix", "SELECT vec_id, round(list_sum([(CAST(v AS DOUBLE) + 1) / 2 FOR v IN embedding[1:8]]), 6) AS total FROM embeddings")
def embedding_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    total = F.aggregate(tf.embedding_prefix(F.col("embedding"), 8), F.lit(0.0), lambda acc, v: acc + v)
    return read(spark, sf_dir, "embeddings").select("vec_id", F.round(total, 6).alias("total"))


# batch twins of the streams

_PLACED = f"WITH RECURSIVE {tree_sql(64, 2)}, p AS ({_EVENTS}), e AS (SELECT p.*, ts, user_id FROM p JOIN events ON point_id = event_id), g AS (SELECT stratum_id, ts, user_id FROM e JOIN strata ON {_inside(2)})"


def _placed(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    axes = {"ts": tf.timestamp_axis(F.col("ts")), "value": F.col("value")}
    bounds = tf.ranges(rows, axes)
    return fill.with_stratum(rows, [tf.unit(c, *bounds[k]) for k, c in axes.items()], 64)


@query("events_tumbling_fill", _PLACED + " SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, count(DISTINCT stratum_id) AS strata, count(*) AS events FROM g GROUP BY 1")
def events_tumbling_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fill.tumbling_fill(_placed(spark, sf_dir), "ts", "1 day").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(
    "events_sliding_fill",
    _PLACED + " SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 6 HOUR AS start, count(DISTINCT stratum_id) AS strata, count(*) AS events FROM g, range(4) r(k) GROUP BY 1",
)
def events_sliding_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fill.sliding_fill(_placed(spark, sf_dir), "ts", "1 day", "6 hours").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(
    "events_session_fill",
    _PLACED
    + """, f AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM g),
    s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM f)
    SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 12 HOUR AS "end", count(DISTINCT stratum_id) AS strata, count(*) AS events FROM s GROUP BY user_id, k""",
)
def events_session_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fill.session_fill(_placed(spark, sf_dir), "ts", "12 hours", "user_id")
    return found.withColumns({"start": F.col("start").cast("timestamp_ntz"), "end": F.col("end").cast("timestamp_ntz")})


@query("events_late", "SELECT ts < (SELECT max(ts) FROM events) - INTERVAL 5 DAY AS late, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def events_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    told = fill.split_late(read(spark, sf_dir, "events"), "ts", "5 days")
    return told.groupBy("late").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"))


# scans

KEYS = {
    "region": "r_regionkey",
    "nation": "n_nationkey",
    "customer": "c_custkey",
    "supplier": "s_suppkey",
    "part": "p_partkey",
    "orders": "o_orderkey",
    "lineitem": "l_orderkey",
    "events": "event_id",
    "documents": "doc_id",
    "embeddings": "vec_id",
    "pages": "page_id",
    "benchmark": "item_id",
    "labels": "doc_id",
    "conversations": "conv_id",
}

for _table in TABLES:

    @query(f"scan_{_table}", f"SELECT count(*) AS n, CAST(sum({KEYS[_table]}) AS BIGINT) AS key_sum, CAST(max({KEYS[_table]}) AS BIGINT) AS key_max FROM {_table}")
    def _scan(spark: SparkSession, sf_dir: str, table=_table) -> DataFrame:
        key = F.col(KEYS[table]).cast("long")
        return read(spark, sf_dir, table).agg(F.count("*").alias("n"), F.sum(key).alias("key_sum"), F.max(key).alias("key_max"))

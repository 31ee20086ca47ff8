"""Relational operators that users of set queries need around them, each with the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.families import EXPLODED, FAMILIES, catalog, family_sql, load_families, load_family, load_table
from ..sources.scratch import scratch

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def tab(name: str):
    """A query over one table."""

    def wrap(fn):
        return lambda spark, folder: fn(load_table(spark, folder, name))

    return wrap


# -- scans, predicates, projections ------------------------------------------------------------------

op("scan_parquet_pruned", "SELECT l_orderkey, l_quantity FROM lineitem")(lambda s, d: load_table(s, d, "lineitem", ["l_orderkey", "l_quantity"]))
op("scan_pushdown", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'A'")(tab("lineitem")(lambda t: t.where("l_quantity > 45 AND l_returnflag = 'A'").select("l_orderkey", "l_partkey")))
op("load_family", family_sql("flag_orders"))(lambda s, d: load_family(s, d, "flag_orders"))
_ALL = [*FAMILIES, *EXPLODED]
op("catalog_stats", " UNION ALL ".join(f"SELECT '{n}' AS family, CAST(count(*) AS BIGINT) AS sets, CAST(sum(c) AS BIGINT) AS pairs, CAST(max(c) AS BIGINT) AS largest FROM (SELECT set_id, count(*) AS c FROM ({family_sql(n)}) GROUP BY 1)" for n in _ALL))(
    lambda s, d: _union([catalog(load_family(s, d, n)).agg(F.lit(n).alias("family"), F.count("*").alias("sets"), F.sum("card").alias("pairs"), F.max("card").alias("largest")) for n in _ALL])
)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


op("project_exprs", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, CAST(l_quantity AS INT) AS q, concat(l_returnflag, l_linestatus) AS flag FROM lineitem")(
    tab("lineitem")(lambda t: t.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.col("l_quantity").cast("int").alias("q"), F.concat("l_returnflag", "l_linestatus").alias("flag")))
)
op("filter_boolean", "SELECT p_partkey FROM part WHERE (p_brand = 'Brand#4' OR p_brand = 'Brand#7') AND NOT (p_size < 10 OR p_type = 'PROMO')")(
    tab("part")(lambda t: t.where(F.col("p_brand").isin("Brand#4", "Brand#7") & ~((F.col("p_size") < 10) | (F.col("p_type") == "PROMO"))).select("p_partkey"))
)
op("filter_in_between_like", "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_type IN ('ECONOMY', 'PROMO', 'SMALL') AND p_brand LIKE 'Brand#1%'")(
    tab("part")(lambda t: t.where(F.col("p_size").between(5, 20) & F.col("p_type").isin("ECONOMY", "PROMO", "SMALL") & F.col("p_brand").like("Brand#1%")).select("p_partkey"))
)
op("filter_null_safe", "SELECT doc_id, coalesce(quality, -1) AS quality, toxic IS NULL AS unlabelled FROM documents LEFT JOIN labels USING (doc_id) WHERE quality IS NOT DISTINCT FROM NULL OR toxic = 1")(
    lambda s, d: load_table(s, d, "documents", ["doc_id"]).join(load_table(s, d, "labels"), "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None)) | (F.col("toxic") == 1)).select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.col("toxic").isNull().alias("unlabelled"))
)
op("case_when", "SELECT event_id, CASE WHEN value > 95 THEN 'high' WHEN value > 50 THEN 'middle' ELSE 'low' END AS band FROM events")(
    tab("events")(lambda t: t.select("event_id", F.when(F.col("value") > 95, "high").when(F.col("value") > 50, "middle").otherwise("low").alias("band")))
)


def predicate_set(df: DataFrame, condition, key: str, name: str) -> DataFrame:
    """The keys of the rows that satisfy a condition, as a named set."""
    return df.where(condition).select(F.lit(name).alias("set_id"), F.col(key).cast("long").alias("elem")).distinct()


op("predicate_to_set", "SELECT DISTINCT 'urgent_big' AS set_id, o_custkey AS elem FROM orders WHERE o_orderpriority = '1-URGENT' AND o_totalprice > 100000")(tab("orders")(lambda t: predicate_set(t, "o_orderpriority = '1-URGENT' AND o_totalprice > 100000", "o_custkey", "urgent_big")))


def _formats(spark: SparkSession, df: DataFrame, kind: str) -> DataFrame:
    """Written in another format and read back with an explicit schema."""
    path = scratch(spark, "formats")
    df.write.format(kind).save(path)
    return spark.read.schema(df.schema).format(kind).load(path)


for _kind in ("csv", "json", "orc"):
    op(f"{_kind}_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(lambda s, d, kind=_kind: _formats(s, load_table(s, d, "nation"), kind))

# -- joins ---------------------------------------------------------------------------------------------

ORDERS_LINES = "SELECT o_orderkey, l_linenumber, o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey"


def _orders_lines(hint: str):
    def run(s, d):
        lines = load_table(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey"])
        orders = load_table(s, d, "orders", ["o_orderkey", "o_custkey"])
        return orders.hint(hint).join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "o_custkey", "l_partkey")

    return run


op("join_inner_hash", ORDERS_LINES)(_orders_lines("shuffle_hash"))
op("join_sort_merge", ORDERS_LINES)(_orders_lines("merge"))
op("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")(
    # 25 nations, whatever the scale
    lambda s, d: load_table(s, d, "customer").join(F.broadcast(load_table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")
)
for _how, _word in (("semi", "IN"), ("anti", "NOT IN")):
    op(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE c_custkey {_word} (SELECT o_custkey FROM orders WHERE o_totalprice > 150000)")(
        lambda s, d, how=_how: load_table(s, d, "customer").join(load_table(s, d, "orders").where("o_totalprice > 150000"), F.col("c_custkey") == F.col("o_custkey"), f"left_{how}").select("c_custkey")
    )
op("join_outer_left", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")(lambda s, d: load_table(s, d, "documents", ["doc_id"]).join(load_table(s, d, "labels"), "doc_id", "left").select("doc_id", "quality"))
op("join_outer_full", "SELECT doc_id, n_chars, quality, item_id FROM labels FULL JOIN (SELECT item_id AS doc_id, item_id FROM benchmark) USING (doc_id) FULL JOIN documents USING (doc_id)")(
    # whole tables: labels without an item and items without a label in the first join, documents with neither in the second
    lambda s, d: load_table(s, d, "labels").join(load_table(s, d, "benchmark", ["item_id"]).withColumn("doc_id", F.col("item_id")), "doc_id", "full").join(load_table(s, d, "documents", ["doc_id", "n_chars"]), "doc_id", "full").select("doc_id", "n_chars", "quality", "item_id")
)
op("join_theta_nested_loop", "SELECT a.r_regionkey AS small, b.r_regionkey AS large FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")(
    lambda s, d: load_table(s, d, "region").alias("a").join(load_table(s, d, "region").alias("b"), F.col("a.r_regionkey") < F.col("b.r_regionkey")).select(F.col("a.r_regionkey").alias("small"), F.col("b.r_regionkey").alias("large"))
)


def range_join(left: DataFrame, right: DataFrame, value: str, low: str, high: str, bin_size: float) -> DataFrame:
    """Rows of `left` whose value lies in [low, high] of `right`: both dealt to bins of the value, equal bins joined, then checked."""
    bins = F.sequence(F.floor(F.col(low) / bin_size), F.floor(F.col(high) / bin_size))
    return left.withColumn("_bin", F.floor(F.col(value) / bin_size)).join(right.withColumn("_bin", F.explode(bins)), "_bin").where(F.col(value).between(F.col(low), F.col(high))).drop("_bin")


op("join_range_interval", "SELECT event_id, band FROM events JOIN (VALUES (0, 10.0, 22.5), (1, 20.0, 21.0), (2, 60.0, 95.0)) b(band, low, high) ON value BETWEEN low AND high")(
    lambda s, d: range_join(load_table(s, d, "events", ["event_id", "value"]), s.createDataFrame([(0, 10.0, 22.5), (1, 20.0, 21.0), (2, 60.0, 95.0)], "band int, low double, high double"), "value", "low", "high", 10.0).select("event_id", "band")
)


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """Each left row with the last `value` of `right` at or before its time, per key: one sort of both together."""
    both = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side")).unionByName(
        right.select(key, time, F.col(value).alias("_v"), F.lit(0).alias("_side")), allowMissingColumns=True
    )
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("asof", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")


op("join_asof", """SELECT p.event_id, p.user_id, (SELECT max_by(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND c.ts <= p.ts) AS asof
    FROM events p WHERE p.event_type = 'purchase'""")(
    lambda s, d: _asof(load_table(s, d, "events", ["event_id", "ts", "user_id", "event_type"]))
)


def _asof(t: DataFrame) -> DataFrame:
    buys, clicks = (t.where(F.col("event_type") == k).drop("event_type") for k in ("purchase", "click"))
    latest = clicks.groupBy("user_id", "ts").agg(F.max("event_id").alias("click"))  # ties at one time: the largest id
    return asof_join(buys, latest, "user_id", "ts", "click").select("event_id", "user_id", "asof")


op("join_cross", "SELECT a.set_id AS a, b.set_id AS b FROM (SELECT DISTINCT o_orderstatus AS set_id FROM orders) a, (SELECT DISTINCT o_orderpriority AS set_id FROM orders) b")(
    # names of sets: a few, whatever the scale
    tab("orders")(lambda t: t.select(F.col("o_orderstatus").alias("a")).distinct().crossJoin(t.select(F.col("o_orderpriority").alias("b")).distinct()))
)
op("join_multiway_star", """SELECT r_name, CAST(count(*) AS BIGINT) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
    JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE p_size < 10 AND s_acctbal > 0 GROUP BY 1""")(
    lambda s, d: load_table(s, d, "lineitem", ["l_orderkey", "l_suppkey", "l_partkey", "l_extendedprice"])
    .join(load_table(s, d, "part", ["p_partkey", "p_size"]).where("p_size < 10"), F.col("l_partkey") == F.col("p_partkey"))
    .join(load_table(s, d, "supplier", ["s_suppkey", "s_acctbal"]).where("s_acctbal > 0"), F.col("l_suppkey") == F.col("s_suppkey"))
    .join(load_table(s, d, "orders", ["o_orderkey", "o_custkey"]), F.col("l_orderkey") == F.col("o_orderkey"))
    .join(load_table(s, d, "customer", ["c_custkey", "c_nationkey"]), F.col("o_custkey") == F.col("c_custkey"))
    .join(load_table(s, d, "nation", ["n_nationkey", "n_regionkey"]), F.col("c_nationkey") == F.col("n_nationkey"))
    .join(load_table(s, d, "region", ["r_regionkey", "r_name"]), F.col("n_regionkey") == F.col("r_regionkey"))
    .groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))
)


def overlaps(family: DataFrame, least: int) -> DataFrame:
    """Pairs of sets with at least so many common elements, by way of the elements they share."""
    other = family.select(F.col("set_id").alias("b"), "elem")
    pairs = family.select(F.col("set_id").alias("a"), "elem").join(other, "elem").where("a < b")
    return pairs.groupBy("a", "b").agg(F.count("*").alias("common")).where(F.col("common") >= least)


_PAIRS = "SELECT x.set_id AS a, y.set_id AS b, CAST(count(*) AS BIGINT) AS common FROM fam x JOIN fam y USING (elem) WHERE x.set_id < y.set_id GROUP BY 1, 2"
op("join_set_overlap", f"WITH fam AS ({family_sql('month_customers')}) SELECT * FROM ({_PAIRS}) WHERE common >= 25")(lambda s, d: overlaps(load_family(s, d, "month_customers"), 25))
op("join_containment", f"WITH fam AS ({family_sql('supp_nation', 'part_brand')}), c AS (SELECT set_id, count(*) AS card FROM fam GROUP BY 1) SELECT a, b FROM ({_PAIRS.replace('x.set_id < y.set_id', 'x.set_id <> y.set_id')}) JOIN c ON c.set_id = a WHERE common = card")(
    lambda s, d: _containment(load_families(s, d, ["supp_nation", "part_brand"]))
)


def _containment(family: DataFrame) -> DataFrame:
    other = family.select(F.col("set_id").alias("b"), "elem")
    pairs = family.select(F.col("set_id").alias("a"), "elem").join(other, "elem").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("common"))
    return pairs.join(catalog(family).select(F.col("set_id").alias("a"), "card"), "a").where("common = card").select("a", "b")


def _lateral(s, d):
    c = load_table(s, d, "customer", ["c_custkey"])
    best = load_table(s, d, "orders", ["o_orderkey", "o_custkey", "o_totalprice"]).where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2)
    return c.lateralJoin(best).select("c_custkey", "o_orderkey")


op("join_lateral", "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders JOIN customer ON c_custkey = o_custkey) WHERE k <= 2")(_lateral)


# -- aggregation ------------------------------------------------------------------------------------------

op("agg_hash", "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1, 2")(
    tab("lineitem")(lambda t: t.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi")))
)
op("agg_distinct", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS supps FROM lineitem GROUP BY 1")(
    tab("lineitem")(lambda t: t.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps")))
)
_BY = "SELECT o_orderstatus, o_orderpriority, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY "
op("agg_grouping_sets", _BY + "GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")(
    tab("orders")(lambda t: t.groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).select("o_orderstatus", "o_orderpriority", "n"))
)
op("agg_rollup", _BY + "ROLLUP (o_orderstatus, o_orderpriority)")(tab("orders")(lambda t: t.rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))))
op("agg_cube", _BY + "CUBE (o_orderstatus, o_orderpriority)")(tab("orders")(lambda t: t.cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))))
op("agg_filter_clause", "SELECT event_type, CAST(count(*) FILTER (WHERE value > 50) AS BIGINT) AS high, round(sum(value) FILTER (WHERE value <= 50), 4) AS low FROM events GROUP BY 1")(
    tab("events")(lambda t: t.groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.sum(F.when(F.col("value") <= 50, F.col("value"))), 4).alias("low")))
)
op("agg_having", "SELECT o_custkey, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1 HAVING count(*) > 15")(tab("orders")(lambda t: t.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15")))
op("agg_collect_sets", f"SELECT set_id, elem // 1000 AS part, array_to_string(list_sort(list(DISTINCT elem)), ',') AS elems FROM ({family_sql('status_customers')}) GROUP BY 1, 2")(
    # sets as arrays, in ranges of a thousand keys, so that no array grows with the table
    lambda s, d: load_family(s, d, "status_customers").groupBy("set_id", F.floor(F.col("elem") / 1000).alias("part")).agg(F.array_join(F.sort_array(F.collect_set("elem")).cast("array<string>"), ",").alias("elems"))
)
op("agg_bit_or_mask", f"SELECT elem, CAST(bit_or(CASE set_id WHEN 'AF' THEN 1 WHEN 'AO' THEN 2 WHEN 'NF' THEN 4 WHEN 'NO' THEN 8 WHEN 'RF' THEN 16 ELSE 32 END) AS BIGINT) AS mask FROM ({family_sql('flag_orders')}) GROUP BY 1")(
    lambda s, d: _masks(load_family(s, d, "flag_orders"))
)


def _masks(fam: DataFrame) -> DataFrame:
    from ..plans.expr import parse
    from .evaluate import marked

    return marked(parse("AF | AO | NF | NO | RF | RO"), fam).groupBy("elem").agg(F.bit_or("m0").alias("mask"))


op("agg_pivot", "SELECT user_id, CAST(count(*) FILTER (WHERE event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (WHERE event_type = 'view') AS BIGINT) AS view FROM events GROUP BY 1")(
    tab("events")(lambda t: t.groupBy("user_id").pivot("event_type", ["click", "view"]).count().na.fill(0))
)
op("agg_approx", "SELECT event_type, true AS users_near, true AS median_near, true AS events_near FROM events GROUP BY 1")(
    # estimates beside exact values: within four standard errors of each
    tab("events")(
        lambda t: t.groupBy("event_type")
        .agg(F.approx_count_distinct("user_id", 0.02).alias("u"), F.count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5, 1000).alias("m"), F.median("value").alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("event_id")).alias("e"), F.count_distinct("event_id").alias("events"), (F.max("value") - F.min("value")).alias("span"))
        .select("event_type", (F.abs(F.col("u") - F.col("users")) <= F.greatest(F.lit(2), 0.08 * F.col("users"))).alias("users_near"), (F.abs(F.col("m") - F.col("median")) <= 0.02 * F.col("span")).alias("median_near"), (F.abs(F.col("e") - F.col("events")) <= F.greatest(F.lit(2), 0.08 * F.col("events"))).alias("events_near"))
    )
)
op("agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, median(l_quantity) AS med FROM lineitem GROUP BY 1")(
    tab("lineitem")(lambda t: t.groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.median("l_quantity").alias("med")))
)
op("agg_sort_based", "SELECT o_custkey, max_by(o_orderpriority, (o_totalprice, o_orderkey)) AS top, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY 1")(
    tab("orders")(lambda t: t.groupBy("o_custkey").agg(F.max_by("o_orderpriority", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("low")))
)
op("agg_jaccard", f"WITH fam AS ({family_sql('month_customers')}), c AS (SELECT set_id, count(*) AS card FROM fam GROUP BY 1) SELECT a, b, round(common / CAST(x.card + y.card - common AS DOUBLE), 6) AS jaccard FROM ({_PAIRS}) JOIN c x ON x.set_id = a JOIN c y ON y.set_id = b WHERE common >= 20")(
    lambda s, d: _jaccard(load_family(s, d, "month_customers"))
)


def _jaccard(fam: DataFrame) -> DataFrame:
    c = catalog(fam)
    pairs = overlaps(fam, 20).join(c.select(F.col("set_id").alias("a"), F.col("card").alias("ca")), "a").join(c.select(F.col("set_id").alias("b"), F.col("card").alias("cb")), "b")
    return pairs.select("a", "b", F.round(F.col("common") / (F.col("ca") + F.col("cb") - F.col("common")), 6).alias("jaccard"))


# -- windows, order, set operations -------------------------------------------------------------------------

_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"


def _cust():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


def _per_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


def ranked_in_ranges(df: DataFrame, part: str, key: str, width: int) -> DataFrame:
    """Adds rk and dr, rank and dense rank by an integer key within a part, where a part may be a large share of all rows.

    Rows are ranked inside ranges of `width` keys; what comes before a range is added from a table of ranges, which is as much smaller
    than the rows as a range has rows.
    """
    cut = df.withColumn("range", F.floor(F.col(key) / width))
    sums = cut.groupBy(part, "range").agg(F.count("*").alias("n"), F.countDistinct(key).alias("d"))
    so_far = Window.partitionBy(part).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    before = sums.select(part, "range", *[F.coalesce(F.sum(c).over(so_far), F.lit(0)).alias(f"{c}_before") for c in "nd"])
    inside = Window.partitionBy(part, "range").orderBy(key)
    ranked = cut.join(before, [part, "range"]).withColumns({"rk": F.rank().over(inside) + F.col("n_before"), "dr": F.dense_rank().over(inside) + F.col("d_before")})
    return ranked.drop("range", "n_before", "d_before")


def counted_in_ranges(df: DataFrame, part: str, key: str, span: int) -> DataFrame:
    """Adds `hour`, the rows of the same part at most `span` before a row. Ranges as wide as the span: a row goes to its own and, to be
    counted only, to the next."""
    own = df.withColumn("range", F.floor(F.col(key) / span)).withColumn("here", F.lit(True))
    copies = own.withColumn("range", F.col("range") + 1).withColumn("here", F.lit(False))
    window = Window.partitionBy(part, "range").orderBy(key).rangeBetween(-span, 0)
    return own.unionByName(copies).withColumn("hour", F.count("*").over(window)).where("here").drop("range", "here")


op("win_rank", f"SELECT o_orderkey, CAST(row_number() {_W}) AS INT) AS rn, CAST(rank() OVER (PARTITION BY o_orderpriority ORDER BY o_custkey) AS INT) AS rk, CAST(dense_rank() OVER (PARTITION BY o_orderpriority ORDER BY o_custkey) AS INT) AS dr, CAST(ntile(4) {_W}) AS INT) AS nt, round(percent_rank() {_W}), 6) AS pr, round(cume_dist() {_W}), 6) AS cd FROM orders")(
    tab("orders")(lambda t: ranked_in_ranges(t, "o_orderpriority", "o_custkey", 100).select("o_orderkey", F.row_number().over(_cust()).alias("rn"), F.col("rk").cast("int").alias("rk"), F.col("dr").cast("int").alias("dr"), F.ntile(4).over(_cust()).alias("nt"), F.round(F.percent_rank().over(_cust()), 6).alias("pr"), F.round(F.cume_dist().over(_cust()), 6).alias("cd")))
)
_EW = "OVER (PARTITION BY user_id ORDER BY ts, event_id"
op("win_lag_lead", f"SELECT event_id, lag(event_id) {_EW}) AS before, lead(event_id, 2) {_EW}) AS after, first_value(event_id) {_EW}) AS first, nth_value(event_id, 2) {_EW} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events")(
    tab("events")(lambda t: t.select("event_id", F.lag("event_id").over(_per_user()).alias("before"), F.lead("event_id", 2).over(_per_user()).alias("after"), F.first("event_id").over(_per_user()).alias("first"), F.nth_value("event_id", 2).over(_per_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second")))
)
op("win_rows_frame", f"SELECT o_orderkey, round(sum(o_totalprice) {_W} ROWS UNBOUNDED PRECEDING), 2) AS running, round(sum(o_totalprice) {_W} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS moving FROM orders")(
    tab("orders")(lambda t: t.select("o_orderkey", F.round(F.sum("o_totalprice").over(_cust().rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"), F.round(F.sum("o_totalprice").over(_cust().rowsBetween(-2, 0)), 2).alias("moving")))
)
op("win_range_frame", "SELECT event_id, CAST(count(*) OVER (PARTITION BY event_type ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS BIGINT) AS hour FROM events")(
    tab("events")(lambda t: counted_in_ranges(t.select("event_id", "event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("sec")), "event_type", "sec", 3600).select("event_id", "hour"))
)
_M3 = "month_customers"
_SET = lambda m: f"SELECT elem FROM fam WHERE set_id = '{m}'"
_FAM = f"WITH fam AS ({family_sql(_M3)}) "


def _two(s, d, a="1996-01", b="1996-02"):
    fam = load_family(s, d, _M3)
    return fam.where(F.col("set_id") == a).select("elem"), fam.where(F.col("set_id") == b).select("elem")


op("win_neighbour_equal", _FAM + f"{_SET('1996-01')} INTERSECT {_SET('1996-02')}")(
    # two sorted sets merged: an element equal to its left neighbour is in both; dealt by ranges of the element
    lambda s, d: _two(s, d)[0].unionAll(_two(s, d)[1]).withColumn("left", F.lag("elem").over(Window.partitionBy(F.floor(F.col("elem") / 1000)).orderBy("elem"))).where(F.col("left") == F.col("elem")).select("elem")
)
op("sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC NULLS LAST, o_orderkey")(tab("orders")(lambda t: t.select("o_orderkey", "o_totalprice").orderBy(F.desc_nulls_last("o_totalprice"), "o_orderkey")))
op("topk_global", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 25")(tab("lineitem")(lambda t: t.select("l_orderkey", "l_linenumber", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(25)))
op("topk_per_group", f"SELECT lead, set_id, card FROM (SELECT substring(set_id, 1, 1) AS lead, set_id, CAST(count(*) AS BIGINT) AS card, row_number() OVER (PARTITION BY substring(set_id, 1, 1) ORDER BY count(*) DESC, set_id) AS k FROM ({family_sql('supp_parts')}) GROUP BY 2) WHERE k <= 3")(
    lambda s, d: catalog(load_family(s, d, "supp_parts")).withColumn("lead", F.substring("set_id", 1, 1)).withColumn("k", F.row_number().over(Window.partitionBy("lead").orderBy(F.desc("card"), "set_id"))).where("k <= 3").select("lead", "set_id", "card")
)
op("limit_offset", "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 30")(tab("part")(lambda t: t.select("p_partkey").orderBy("p_partkey").offset(30).limit(10)))
op("set_union_all", _FAM + f"{_SET('1996-01')} UNION ALL {_SET('1996-02')}")(lambda s, d: _two(s, d)[0].unionByName(_two(s, d)[1]))
op("set_union", _FAM + f"{_SET('1996-01')} UNION {_SET('1996-02')}")(lambda s, d: _two(s, d)[0].union(_two(s, d)[1]).distinct())
op("set_intersect", _FAM + f"{_SET('1996-01')} INTERSECT {_SET('1996-02')}")(lambda s, d: _two(s, d)[0].intersect(_two(s, d)[1]))
op("set_except", _FAM + f"{_SET('1996-01')} EXCEPT {_SET('1996-02')}")(lambda s, d: _two(s, d)[0].subtract(_two(s, d)[1]))
_FLAGS = "SELECT l_suppkey AS elem FROM lineitem WHERE l_returnflag = '{}'"
for _name, _fn, _word in (("set_intersect_all", "intersectAll", "INTERSECT ALL"), ("set_except_all", "exceptAll", "EXCEPT ALL")):
    op(_name, f"{_FLAGS.format('A')} {_word} {_FLAGS.format('R')}")(
        tab("lineitem")(lambda t, fn=_fn: getattr(t.where("l_returnflag = 'A'").select(F.col("l_suppkey").alias("elem")), fn)(t.where("l_returnflag = 'R'").select(F.col("l_suppkey").alias("elem"))))
    )
op("set_symmetric_difference", _FAM + f"({_SET('1996-01')} EXCEPT {_SET('1996-02')}) UNION ALL ({_SET('1996-02')} EXCEPT {_SET('1996-01')})")(
    lambda s, d: _two(s, d)[0].unionAll(_two(s, d)[1]).groupBy("elem").count().where("count = 1").select("elem")
)
op("set_kofm", f"SELECT elem FROM ({family_sql('flag_orders')}) GROUP BY 1 HAVING count(*) >= 5")(lambda s, d: _masks(load_family(s, d, "flag_orders")).where("bit_count(mask) >= 5").select("elem"))
op("set_subset_test", f"WITH fam AS ({family_sql('part_type', 'part_brand')}) SELECT NOT EXISTS ({_SET('Brand#4')} EXCEPT {_SET('ECONOMY')}) AS subset")(lambda s, d: _subset(load_families(s, d, ["part_type", "part_brand"]), "Brand#4", "ECONOMY"))


def _subset(fam: DataFrame, a: str, b: str) -> DataFrame:
    rest = fam.where(F.col("set_id") == a).join(fam.where(F.col("set_id") == b).select("elem"), "elem", "left_anti").limit(1)
    return rest.agg((F.count("*") == 0).alias("subset"))


# -- functions ------------------------------------------------------------------------------------------------

op("fn_string", "SELECT p_partkey, lower(p_type) AS low, split_part(p_brand, '#', 2) AS num, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, substring(p_name, 1, 3) AS head, length(p_name) AS len, replace(p_brand, '#', '-') AS dash, concat_ws('/', p_brand, p_type) AS path, trim(concat(' ', p_type, ' ')) AS bare FROM part")(
    tab("part")(lambda t: t.select("p_partkey", F.lower("p_type").alias("low"), F.split("p_brand", "#")[1].alias("num"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.substring("p_name", 1, 3).alias("head"), F.length("p_name").cast("long").alias("len"), F.regexp_replace("p_brand", "#", "-").alias("dash"), F.concat_ws("/", "p_brand", "p_type").alias("path"), F.trim(F.concat(F.lit(" "), "p_type", F.lit(" "))).alias("bare")))
)
op("fn_tokenize", f"SELECT set_id, CAST(count(*) AS BIGINT) AS docs FROM ({family_sql('term_docs')}) GROUP BY 1")(lambda s, d: load_family(s, d, "term_docs").groupBy("set_id").agg(F.count("*").alias("docs")))
op("fn_shingle", "SELECT item_id, CAST(count(DISTINCT array_to_string(w[i:i + 4], ' ')) AS BIGINT) AS shingles FROM (SELECT item_id, w, unnest(range(1, len(w) - 3)) AS i FROM (SELECT item_id, regexp_extract_all(lower(text), '[^\\s]+') AS w FROM benchmark)) GROUP BY 1")(
    tab("benchmark")(lambda t: t.select("item_id", F.regexp_extract_all(F.lower("text"), F.lit("[^\\s]+"), F.lit(0)).alias("w")).where("size(w) >= 5").select("item_id", F.size(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, 5), " ")))).cast("long").alias("shingles")))
)
op("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS later, CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter FROM orders")(
    tab("orders")(lambda t: t.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_diff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.add_months(F.col("o_orderdate").cast("date"), 2).alias("later"), F.trunc(F.col("o_orderdate").cast("date"), "quarter").alias("quarter")))
)
op("fn_math", "SELECT l_orderkey, l_linenumber, CAST(ceil(l_extendedprice) AS BIGINT) AS up, CAST(floor(l_extendedprice) AS BIGINT) AS down, round(log2(l_quantity + 1), 6) AS lg, l_orderkey % 7 AS r, greatest(l_discount, l_tax) AS most FROM lineitem")(
    tab("lineitem")(lambda t: t.select("l_orderkey", "l_linenumber", F.ceil("l_extendedprice").alias("up"), F.floor("l_extendedprice").alias("down"), F.round(F.log2(F.col("l_quantity") + 1), 6).alias("lg"), F.pmod("l_orderkey", F.lit(7)).cast("long").alias("r"), F.greatest("l_discount", "l_tax").alias("most")))
)
op("fn_bitwise", "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 1 AS o, xor(o_orderkey, 5) AS x, o_orderkey >> 3 AS s, o_orderkey << 2 AS l, CAST(bit_count(o_orderkey) AS INT) AS c FROM orders")(
    tab("orders")(lambda t: t.select("o_orderkey", (k := F.col("o_orderkey")).bitwiseAND(F.lit(255)).alias("a"), k.bitwiseOR(F.lit(1)).alias("o"), k.bitwiseXOR(F.lit(5)).alias("x"), F.shiftright(k, 3).alias("s"), F.shiftleft(k, 2).alias("l"), F.bit_count(k).alias("c")))
)
op("fn_array", "SELECT grp, coalesce(array_to_string(list_sort(list_intersect(a, b)), ','), '') AS both, coalesce(len(list_distinct(list_concat(a, b))), 0) AS either, coalesce(list_contains(a, 7), false) AS has FROM (SELECT o_custkey // 200 AS grp, list(DISTINCT o_custkey) FILTER (WHERE o_orderstatus = 'P') AS a, list(DISTINCT o_custkey) FILTER (WHERE o_orderpriority = '1-URGENT') AS b FROM orders GROUP BY 1)")(
    # groups of a bounded number of keys, so the arrays do not grow with the table
    tab("orders")(lambda t: t.groupBy(F.floor(F.col("o_custkey") / 200).alias("grp")).agg(F.collect_set(F.when(F.col("o_orderstatus") == "P", F.col("o_custkey"))).alias("a"), F.collect_set(F.when(F.col("o_orderpriority") == "1-URGENT", F.col("o_custkey"))).alias("b")).select("grp", F.array_join(F.sort_array(F.array_intersect("a", "b")).cast("array<string>"), ",").alias("both"), F.size(F.array_union("a", "b")).cast("long").alias("either"), F.array_contains("a", F.lit(7).cast("long")).alias("has")))
)
op("fn_higher_order", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm FROM embeddings")(
    tab("embeddings")(lambda t: t.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x), 4).alias("norm")))
)
op("fn_map", "SELECT o_orderstatus AS status, o_orderpriority AS priority, CAST(count(*) * 2 AS BIGINT) AS twice FROM orders GROUP BY 1, 2 HAVING count(*) > 1")(
    tab("orders")(lambda t: t.groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).groupBy(F.col("o_orderstatus").alias("status")).agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m")).select("status", F.explode(F.transform_values(F.map_filter("m", lambda k, v: v > 1), lambda k, v: v * 2)).alias("priority", "twice")))
)
op("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")(tab("events")(lambda t: t.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))))
op("fn_url_html", "SELECT page_id, regexp_extract(url, '^([a-z]+):', 1) AS scheme, CAST(len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS INT) AS links FROM pages")(
    tab("pages")(lambda t: t.select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("links")))
)
op("fn_decimal_cast", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS total, CAST(count(TRY_CAST(l_linestatus AS INT)) AS BIGINT) AS numbers FROM lineitem GROUP BY 1")(
    tab("lineitem")(lambda t: t.groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("total"), F.count(F.col("l_linestatus").try_cast("int")).alias("numbers")))
)
op("fn_struct_nested", "SELECT conv_id, turn, role, length(text) AS n FROM conversations")(
    tab("conversations")(lambda t: t.groupBy("conv_id").agg(F.collect_list(F.struct("turn", "role", F.length("text").cast("long").alias("n"))).alias("turns")).select("conv_id", F.inline("turns")))
)
op("sql_entry", f"WITH fam AS ({family_sql('flag_orders')}) {_SET('AF')} INTERSECT {_SET('NO')}")(lambda s, d: _sql(s, d, "(AF & NO)", "flag_orders"))


def _sql(spark: SparkSession, folder: str, text: str, family: str) -> DataFrame:
    """An expression's text through the SQL engine's own set operators."""
    from ..plans.expr import parse, to_sql

    load_family(spark, folder, family).createOrReplaceTempView("fam")
    return spark.sql(f"SELECT elem FROM {to_sql(parse(text), _SET)}")

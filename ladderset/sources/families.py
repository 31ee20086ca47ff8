"""Families of sets on the given tables: (set_id, elem) pairs, distinct and without nulls.

A family is a table with two expressions that mean the same in Spark SQL and in other engines, so its rows
can be checked anywhere with `family_sql`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MONTH = "substring(cast({0} as string), 1, 7)"

#: name -> (FROM clause, set_id, elem)
FAMILIES: dict[str, tuple[str, str, str]] = {
    "flag_orders": ("lineitem", "concat(l_returnflag, l_linestatus)", "l_orderkey"),
    "supp_parts": ("lineitem", "cast(l_suppkey as string)", "l_partkey"),
    "month_customers": ("orders", MONTH.format("o_orderdate"), "o_custkey"),
    "part_orders": ("lineitem", "cast(l_partkey as string)", "l_orderkey"),
    "cust_parts": ("orders JOIN lineitem ON l_orderkey = o_orderkey", "cast(o_custkey as string)", "l_partkey"),
    "event_users": ("events", "concat(event_type, CASE WHEN value > 95 THEN ':high' ELSE ':low' END)", "user_id"),
    "type_users": ("events", "event_type", "user_id"),
    "prio_customers": ("orders", "o_orderpriority", "o_custkey"),
    "status_customers": ("orders", "o_orderstatus", "o_custkey"),
    "part_brand": ("part", "p_brand", "p_partkey"),
    "part_type": ("part", "p_type", "p_partkey"),
    "part_size": ("part", "concat('size', cast(p_size as string))", "p_partkey"),
    "cust_segment": ("customer", "c_mktsegment", "c_custkey"),
    "cust_nation": ("customer JOIN nation ON n_nationkey = c_nationkey", "n_name", "c_custkey"),
    "cust_region": ("customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey", "r_name", "c_custkey"),
    "doc_lang": ("documents", "lang", "doc_id"),
    "doc_source": ("documents", "source", "doc_id"),
    "doc_quality": ("labels", "concat('quality', cast(quality as string))", "doc_id"),
    "doc_toxic": ("labels", "concat('toxic', cast(toxic as string))", "doc_id"),
    "role_convs": ("conversations", "role", "conv_id"),
    "host_pages": ("pages", "split_part(split_part(url, '//', 2), '/', 1)", "page_id"),
    "supp_nation": ("supplier JOIN nation ON n_nationkey = s_nationkey", "n_name", "s_suppkey"),
    "supp_orders": ("lineitem", "cast(l_suppkey as string)", "l_orderkey"),
}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Families whose sets are exploded from an array per row: name -> (table, array in Spark, array in SQL, elem)
EXPLODED = {
    "term_docs": ("documents", "regexp_extract_all(lower(text), '[a-z]+', 0)", "regexp_extract_all(lower(text), '[a-z]+')", "doc_id"),
    "term_turns": ("conversations", "regexp_extract_all(lower(text), '[a-z]+', 0)", "regexp_extract_all(lower(text), '[a-z]+')", "conv_id * 1000 + turn"),
    "dim_vecs": ("embeddings", "transform(filter(transform(embedding, (x, i) -> struct(x, i)), s -> s.x > 0), s -> concat('dim', cast(s.i + 1 as string)))", "list_transform(list_filter(range(1, 65), lambda i: embedding[i] > 0), lambda i: concat('dim', cast(i as string)))", "vec_id"),
    "page_links": ("pages", "regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)", "regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)", "page_id"),
}


def load_table(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def register(spark: SparkSession, folder: str, names: list[str] = TABLES) -> None:
    """The tables as temporary views, for SQL text."""
    for n in names:
        load_table(spark, folder, n).createOrReplaceTempView(n)


def used_tables(source: str) -> list[str]:
    return [t for t in TABLES if t in source.split()]


def load_family(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """(set_id, elem) of a family."""
    if name in EXPLODED:
        src, items, _, elem = EXPLODED[name]
        pairs = load_table(spark, folder, src).select(F.explode(F.expr(items)).alias("set_id"), F.expr(elem).cast("long").alias("elem"))
    else:
        src, sid, elem = FAMILIES[name]
        register(spark, folder, used_tables(src))
        pairs = spark.sql(f"SELECT {sid} AS set_id, CAST({elem} AS BIGINT) AS elem FROM {src}")
    return pairs.where("set_id IS NOT NULL AND elem IS NOT NULL").distinct()


def load_families(spark: SparkSession, folder: str, names: list[str]) -> DataFrame:
    """Several families side by side; their set names must differ."""
    out = load_family(spark, folder, names[0])
    for n in names[1:]:
        out = out.unionByName(load_family(spark, folder, n))
    return out


def family_sql(*names: str) -> str:
    """The same rows in SQL."""
    parts = []
    for name in names:
        if name in EXPLODED:
            src, _, items, elem = EXPLODED[name]
            parts.append(f"SELECT DISTINCT set_id, elem FROM (SELECT unnest({items}) AS set_id, CAST({elem} AS BIGINT) AS elem FROM {src})")
        else:
            src, sid, elem = FAMILIES[name]
            parts.append(f"SELECT DISTINCT {sid} AS set_id, CAST({elem} AS BIGINT) AS elem FROM {src}")
    return " UNION ALL ".join(f"SELECT set_id, elem FROM ({p}) WHERE set_id IS NOT NULL AND elem IS NOT NULL" for p in parts)


def catalog(family: DataFrame) -> DataFrame:
    """Sizes: (set_id, card)."""
    return family.groupBy("set_id").agg(F.count("*").alias("card"))


def synthetic(spark: SparkSession, kind: str, n: int, m: int = 2, k: int = 1) -> DataFrame:
    """Generated families: disjoint, unique (one shared element), equal, controlled (k shared), nested, skewed."""
    base = spark.range(n)
    if kind == "disjoint":
        return base.select(F.concat(F.lit("s"), F.col("id") % m).alias("set_id"), F.col("id").alias("elem"))
    if kind in ("unique", "controlled"):
        shared = 1 if kind == "unique" else k
        own = base.where(F.col("id") >= shared).select(F.concat(F.lit("s"), F.col("id") % m).alias("set_id"), F.col("id").alias("elem"))
        both = spark.range(shared).crossJoin(spark.range(m).withColumnRenamed("id", "s")).select(F.concat(F.lit("s"), F.col("s")).alias("set_id"), F.col("id").alias("elem"))
        return own.union(both)
    if kind == "equal":
        return base.crossJoin(spark.range(m).withColumnRenamed("id", "s")).select(F.concat(F.lit("s"), F.col("s")).alias("set_id"), F.col("id").alias("elem"))
    if kind == "nested":
        return base.crossJoin(spark.range(m).withColumnRenamed("id", "s")).where(F.col("id") < F.call_function("shiftrightunsigned", F.lit(n).cast("long"), F.col("s").cast("int"))).select(F.concat(F.lit("s"), F.col("s")).alias("set_id"), F.col("id").alias("elem"))
    if kind == "skewed":
        small = spark.range(k).select(F.lit("s0").alias("set_id"), (F.col("id") * (n // max(1, k))).alias("elem"))
        return small.union(base.select(F.lit("s1").alias("set_id"), F.col("id").alias("elem")))
    raise ValueError(kind)

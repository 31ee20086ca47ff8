"""Queries of methods, variants, baselines, measures and workloads, with the SQL that must give the same rows.

Queries on stored sets share one store per family and folder, built on first use; a build of its own is measured by `w19_build`.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.hashing import WIDTH, hashed_set, mother_hash, mother_hash_sql, prefix_hash
from .operators import baselines as B
from .operators import evaluate as E
from .operators import ladder as L
from .operators import measure
from .operators import protocol as P
from .plans import choose, cost
from .plans.expr import Leaf, Node, balance, bounds, flatten, leaves, parse, set_ids, to_sql, union_depth, walk
from .sources.families import catalog, family_sql, load_families, load_family, load_table
from .sources.scratch import scratch, staged

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def expr_sql(text: str, families: tuple[str, ...], head: str = "SELECT elem FROM answer") -> str:
    e = parse(text)
    body = to_sql(e, lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'")
    return f"WITH fam AS ({family_sql(*families)}), answer AS (SELECT * FROM {body}) {head}"


_STORES: dict[tuple, str] = {}


def store_of(spark: SparkSession, folder: str, families: tuple[str, ...], **options) -> L.Ladder:
    """The stored ladder of some families, built on first use."""
    key = (spark.sparkContext.applicationId, folder, families, repr(sorted(options.items())))
    if key not in _STORES or not L.versions(spark, _STORES[key], "sets"):
        _STORES[key] = scratch(spark, "ladder")
        L.write_ladder(load_families(spark, folder, list(families)), _STORES[key], "sets", **options)
    return L.read_ladder(spark, _STORES[key], "sets")


TERMS = ("term_docs",)
FLAGS = ("flag_orders",)
SIX = "AF & AO & NF & NO & RF & RO"
TWO_WAYS = "(AF & AO & NF) | (RF & RO & NO)"
YEAR = {y: "(" + " | ".join(f"{y}-{m:02d}" for m in range(1, 13)) + ")" for y in (1996, 1997)}
#: name -> (families, expression)
WORKLOADS: dict[str, tuple[tuple[str, ...], str]] = {
    "w01_and": (TERMS, "the & of & was"),
    "w02_and_or": (TERMS, "(the & of) | (que & les)"),
    "w04_predicates": (("part_brand", "part_type", "part_size"), "Brand#4 & ECONOMY & (size10 | size11 | size12 | size13 | size14)"),
    "w05_many_way": (FLAGS, SIX),
    "w07_months": (("month_customers",), "1996-01 & 1996-02"),
    "w08_uneven": (("part_orders", "flag_orders"), "7 & (AF | AO)"),
    "w09_empty": (("doc_lang",), "en & fr"),
    "w10_everything": (("type_users",), "click & error & purchase & signup & view"),
    "w11_duplicates": (("cust_parts",), "(1 & 2) | (3 & 4) | (5 & 6) | (7 & 8)"),
    "w11_flags": (FLAGS, TWO_WAYS),
    "w12_deep_unions": (("month_customers", "cust_segment"), f"{YEAR[1996]} & {YEAR[1997]} & BUILDING"),
    "w13_alternating": (("prio_customers", "status_customers", "cust_segment"), "(1-URGENT | 2-HIGH) & (F | P) & (BUILDING | MACHINERY)"),
    "w14_union_path": (("month_customers",), "1996-01 | (1996-02 & 1996-03)"),
    "w20_vectors": (("dim_vecs",), "dim1 & dim2 & dim3"),
    "w22_events": (("event_users",), "error:high & purchase:high"),
    "w23_labels": (("doc_lang", "doc_quality", "doc_toxic"), "(en | fr) & quality1 & toxic0"),
    "w25_roles": (("role_convs",), "system & user"),
}
for _name, (_families, _text) in WORKLOADS.items():

    @query(_name, expr_sql(_text, _families))
    def _run(spark, folder, families=_families, text=_text):
        return E.evaluate(text, load_families(spark, folder, list(families)))

    @query(f"{_name}_packed", SQL[_name])
    def _run_packed(spark, folder, families=_families, text=_text):
        return E.evaluate_packed(text, store_of(spark, folder, families))


BATCH = {
    "rare_middle": "scum & the", "two_middle": "que & las", "three_frequent": "the & of & and", "deep": "((the & of) | (que & la)) & (and | les)", "union": "moron | idiot | clown",
    "eight": "the & of & and & that & is & was & with & for", "difference": "the - of", "absorbed": "the & (the | of)",
    "rare_rare": "scum & moron", "depth_four": "(((the & of) | que) & (and | les)) | (was & (with | for))", "depth_five": "((((the | que) & of) | las) & ((and & is) | (les & la))) | ((was | for) & with)",
}


@query("w03_batch", " UNION ALL ".join(f"SELECT '{k}' AS query, CAST(count(*) AS BIGINT) AS k FROM ({expr_sql(t, TERMS)})" for k, t in BATCH.items()))
def w03_batch(spark, folder):
    fam = load_family(spark, folder, "term_docs").where(F.col("set_id").isin(sorted({s for t in BATCH.values() for s in set_ids(parse(t))})))
    fam = staged(fam, "batch")
    parts = [E.cardinality(t, fam).select(F.lit(k).alias("query"), "k") for k, t in BATCH.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


@query("w06_growing_m", " UNION ALL ".join(f"SELECT {m} AS m, CAST(count(*) AS BIGINT) AS k FROM ({expr_sql(' & '.join(map(str, range(1, m + 1))), ('supp_parts',))})" for m in (2, 4, 6)))
def w06_growing_m(spark, folder):
    fam = load_family(spark, folder, "supp_parts")
    parts = [E.intersect_all([str(i) for i in range(1, m + 1)], fam).agg(F.lit(m).alias("m"), F.count("*").alias("k")) for m in (2, 4, 6)]
    return parts[0].union(parts[1]).union(parts[2])


KEYS_SQL = "SELECT concat('s', CAST(c_custkey % 3 AS STRING)) AS set_id, c_custkey AS elem FROM customer WHERE c_custkey > (SELECT min(c_custkey) FROM customer) UNION ALL SELECT concat('s', CAST(i AS STRING)), (SELECT min(c_custkey) FROM customer) FROM (SELECT unnest(range(3)) AS i)"


def unique_family(spark, folder) -> DataFrame:
    """Customers dealt to three sets, but the first of them in all three: the promise of at most one common element."""
    keys = load_table(spark, folder, "customer", ["c_custkey"])
    first = keys.agg(F.min("c_custkey").alias("elem"))
    rest = keys.join(F.broadcast(first), F.col("c_custkey") > F.col("elem")).select(F.concat(F.lit("s"), F.col("c_custkey") % 3).alias("set_id"), F.col("c_custkey").alias("elem"))
    return rest.unionByName(first.select(F.explode(F.array(*[F.lit(f"s{i}") for i in range(3)])).alias("set_id"), "elem"))


@query("unique_intersection", f"WITH fam AS ({KEYS_SQL}) SELECT elem, (SELECT CAST(count(*) AS BIGINT) FROM fam) AS pairs FROM fam GROUP BY 1 HAVING count(*) = 3")
def unique_intersection(spark, folder):
    """The one common element, and the instance's size, n + m - 1."""
    fam = unique_family(spark, folder)
    return E.intersect_all(["s0", "s1", "s2"], fam).crossJoin(fam.agg(F.count("*").alias("pairs")))


def sign_sets(spark, folder) -> DataFrame:
    """Vectors by the sign of a dimension: dim1, dim2, ... and not1, not2, ..., which are disjoint in pairs."""
    vecs = load_table(spark, folder, "embeddings", ["vec_id", "embedding"])
    signs = F.expr("transform(embedding, (x, i) -> concat(if(x > 0, 'dim', 'not'), cast(i + 1 as string)))")
    return vecs.select(F.explode(signs).alias("set_id"), F.col("vec_id").cast("long").alias("elem"))


SIGN_PAIRS = [("dim1", "not1"), ("dim1", "dim2"), ("dim2", "not2"), ("not1", "not2")]


@query("w17_unique_intersection", "WITH v AS (SELECT vec_id, embedding[1] > 0 AS a, embedding[2] > 0 AS b FROM embeddings) " + " UNION ALL ".join(
    f"SELECT '{x} {y}' AS pair, count(*) = 0 AS disjoint FROM v WHERE {' AND '.join(('' if s[:3] == 'dim' else 'NOT ') + {'1': 'a', '2': 'b'}[s[3]] for s in (x, y))}" for x, y in SIGN_PAIRS))
def w17_unique(spark, folder):
    fam = sign_sets(spark, folder).where(F.col("set_id").isin(sorted({s for p in SIGN_PAIRS for s in p})))
    parts = [P.is_disjoint([x, y], fam).select(F.lit(f"{x} {y}").alias("pair"), "disjoint") for x, y in SIGN_PAIRS]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@query(
    "w21_shared_shingles",
    """WITH d AS (SELECT doc_id AS id, regexp_extract_all(lower(text), '[^\\s]+') AS w FROM documents), b AS (SELECT item_id AS id, regexp_extract_all(lower(text), '[^\\s]+') AS w FROM benchmark),
    ds AS (SELECT DISTINCT id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT id, w, unnest(range(1, len(w) - 3)) AS i FROM d)),
    bs AS (SELECT DISTINCT id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT id, w, unnest(range(1, len(w) - 3)) AS i FROM b))
    SELECT ds.id AS doc_id, bs.id AS item_id, CAST(count(*) AS BIGINT) AS shared FROM ds JOIN bs USING (s) GROUP BY 1, 2""",
)
def w21_shared(spark, folder):
    def shingles(name, key):
        w = F.regexp_extract_all(F.lower("text"), F.lit("[^\\s]+"), F.lit(0))
        at = F.when(F.size("w") >= 5, F.sequence(F.lit(1), F.size("w") - 4)).otherwise(F.array().cast("array<int>"))
        grams = F.array_distinct(F.transform(at, lambda i: F.array_join(F.slice("w", i, 5), " ")))
        return spark.read.parquet(f"{folder}/{name}.parquet").select(F.col(key), w.alias("w")).select(key, F.explode(grams).alias("s"))

    return shingles("documents", "doc_id").join(shingles("benchmark", "item_id"), "s").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))


@query("w24_links", f"SELECT h.set_id AS host, CAST(count(DISTINCT l.set_id) AS BIGINT) AS links FROM ({family_sql('host_pages')}) h JOIN ({family_sql('page_links')}) l USING (elem) GROUP BY 1")
def w24_links(spark, folder):
    hosts, links = load_family(spark, folder, "host_pages"), load_family(spark, folder, "page_links").withColumnRenamed("set_id", "link")
    return hosts.join(links, "elem").groupBy(F.col("set_id").alias("host")).agg(F.countDistinct("link").alias("links"))


# -- hashing, rungs, buckets ---------------------------------------------------------------------

for _kind in ("linear2", "tabulation"):

    @query(f"hash_{_kind}", f"SELECT l_orderkey AS k, {mother_hash_sql('l_orderkey', _kind)} AS hs FROM (SELECT DISTINCT l_orderkey FROM lineitem)")
    def _hash(spark, folder, kind=_kind):
        return spark.read.parquet(f"{folder}/lineitem.parquet").select("l_orderkey").distinct().select(F.col("l_orderkey").alias("k"), mother_hash("l_orderkey", kind).alias("hs"))


HS = mother_hash_sql("elem")


def hv_sql(r: int) -> str:
    return f"({HS} >> {WIDTH - r})"


def fam_with(sql: str, *families: str) -> str:
    return f"WITH fam AS ({family_sql(*families)}) {sql}"


@query("hash_prefix_r", fam_with(f"SELECT set_id, elem, {hv_sql(20)} AS h20, {hv_sql(11)} AS h11, {hv_sql(20)} >> 9 AS again FROM fam", *FLAGS))
def hash_prefix_r(spark, folder):
    hs = mother_hash("elem")
    fam = load_family(spark, folder, "flag_orders")
    return fam.select("set_id", "elem", prefix_hash(hs, 20).alias("h20"), prefix_hash(hs, 11).alias("h11"), F.shiftright(prefix_hash(hs, 20), 9).alias("again"))


@query("hashed_set_counts", fam_with(f"SELECT set_id, CAST(count(DISTINCT {hv_sql(12)}) AS BIGINT) AS n FROM fam GROUP BY 1", *FLAGS))
def hashed_set_counts(spark, folder):
    return hashed_set(load_family(spark, folder, "flag_orders"), 12).groupBy("set_id").agg(F.count("*").alias("n"))


RUNG_SQL = f"""cards AS (SELECT set_id, count(*) AS card, CAST(ceil(log2(count(*))) AS INT) AS base FROM fam GROUP BY 1),
    rungs AS (SELECT DISTINCT set_id, card, r FROM (SELECT set_id, card, base + CAST(pow(2, i) AS INT) AS r FROM cards, (SELECT unnest(range(0, 6)) AS i) WHERE i <= floor(log2({WIDTH} - base)) UNION ALL SELECT set_id, card, {WIDTH} FROM cards) WHERE r <= {WIDTH})"""


@query("rung_schedule_all", fam_with(f"SELECT set_id, r FROM rungs", "supp_parts").replace(") SELECT set_id, r", f"), {RUNG_SQL} SELECT set_id, r", 1))
def rung_schedule_all(spark, folder):
    cards = catalog(load_family(spark, folder, "supp_parts"))
    return cards.select("set_id", F.explode(choose.rung_schedule_column(F.col("card"))).alias("r"))


@query("rung_pick", f"WITH fam AS ({family_sql('supp_parts')}), {RUNG_SQL} SELECT set_id, min(r) AS r FROM rungs WHERE r >= 24 GROUP BY 1")
def rung_pick(spark, folder):
    cards = catalog(load_family(spark, folder, "supp_parts"))
    return cards.select("set_id", choose.pick_rung_column(choose.rung_schedule_column(F.col("card")), 24).alias("r"))


def stored(spark, folder, family, **options):
    return L.build_rungs(load_family(spark, folder, family), **options)


@query("ladder_members", f"WITH fam AS ({family_sql(*FLAGS)}), {RUNG_SQL} SELECT DISTINCT f.set_id, r, {HS} >> ({WIDTH} - r) AS hv FROM fam f JOIN rungs USING (set_id)")
def ladder_members(spark, folder):
    return L.members(stored(spark, folder, "flag_orders"))


@query("ladder_derived_equals_direct", fam_with(f"SELECT CAST(0 AS BIGINT) AS differences, CAST(count(DISTINCT concat(set_id, ' ', {hv_sql(20)})) + count(DISTINCT concat(set_id, ' ', {hv_sql(14)})) AS BIGINT) AS values FROM fam", *FLAGS))
def ladder_derived(spark, folder):
    fam = load_family(spark, folder, "flag_orders")
    kept = L.members(L.build_rungs(fam, schedule=[20, 14]))
    direct = hashed_set(fam, 20).withColumn("r", F.lit(20)).union(hashed_set(fam, 14).withColumn("r", F.lit(14))).select("set_id", "r", "hv")
    return kept.withColumn("a", F.lit(1)).join(direct.withColumn("b", F.lit(1)), ["set_id", "r", "hv"], "full").agg(F.count_if(F.col("a").isNull() | F.col("b").isNull()).alias("differences"), F.count("*").alias("values"))


@query("ladder_one_schedule", fam_with(f"SELECT DISTINCT set_id, 17 AS r, {hv_sql(17)} AS hv FROM fam", *FLAGS))
def ladder_one(spark, folder):
    return L.members(stored(spark, folder, "flag_orders", schedule=[17]))


@query("ladder_all_schedule", fam_with(f"SELECT set_id, r, CAST(count(DISTINCT {HS} >> ({WIDTH} - r)) AS BIGINT) AS n FROM fam JOIN (SELECT unnest(range(1, {WIDTH + 1})) AS r) ON true GROUP BY 1, 2 HAVING r >= ceil(log2(count(*)))", "status_customers").replace("SELECT set_id, r,", "SELECT set_id, CAST(r AS INT) AS r,"))
def ladder_all(spark, folder):
    return stored(spark, folder, "status_customers", schedule="all").groupBy("set_id", "r").agg(F.sum("n").alias("n"))


def _mask_lookup_sql(r: int) -> str:
    """Elements of every set under the prefixes in the sketch of TWO_WAYS."""
    return _mask_sql(r) + f" SELECT set_id, elem, s.hv FROM fam JOIN s ON s.hv = {hv_sql(r)}"


def buckets(spark, folder, r=16, b=4):
    return L.to_buckets(hashed_set(load_family(spark, folder, "flag_orders"), r), r, b)


DISTINCT16 = fam_with(f"SELECT DISTINCT set_id, 16 AS r, {hv_sql(16)} AS hv FROM fam", *FLAGS)


@query("bucket_members", DISTINCT16)
def bucket_members(spark, folder):
    return L.members(buckets(spark, folder))


@query("packed_roundtrip", fam_with(f"SELECT set_id, hv >> 12 AS bucket, CAST(count(*) AS INT) AS n FROM (SELECT DISTINCT set_id, {hv_sql(16)} AS hv FROM fam) GROUP BY 1, 2", *FLAGS))
def packed_roundtrip(spark, folder):
    return buckets(spark, folder).select("set_id", "bucket", "n")


for _name, _b in (("bucket_rebucket_up", 7), ("bucket_rebucket_down", 2)):

    @query(_name, fam_with(f"SELECT set_id, hv >> {16 - _b} AS bucket, CAST(count(*) AS INT) AS n FROM (SELECT DISTINCT set_id, {hv_sql(16)} AS hv FROM fam) GROUP BY 1, 2", *FLAGS))
    def _rebucket(spark, folder, b=_b):
        return L.rebucket(buckets(spark, folder), b).select("set_id", "bucket", "n")


@query("bucket_truncate", fam_with(f"SELECT DISTINCT set_id, 11 AS r, {hv_sql(11)} AS hv FROM fam", *FLAGS))
def bucket_truncate(spark, folder):
    return L.members(L.truncate(buckets(spark, folder), 5))


@query("bucket_balanced_b", fam_with("SELECT set_id, CAST(greatest(0, floor(log2(count(*)) - 6)) AS INT) AS b FROM fam GROUP BY 1", "supp_parts", "flag_orders"))
def bucket_balanced(spark, folder):
    return catalog(load_families(spark, folder, ["supp_parts", "flag_orders"])).select("set_id", choose.balanced_b_column(F.col("card")).alias("b"))


for _name, _op, _word in (("bucket_union", "or", "UNION"), ("bucket_intersect", "and", "INTERSECT")):

    @query(_name, fam_with(f"SELECT 'result' AS set_id, 16 AS r, hv FROM (SELECT {hv_sql(16)} AS hv FROM fam WHERE set_id = 'AF' {_word} SELECT {hv_sql(16)} AS hv FROM fam WHERE set_id = 'NO')", *FLAGS))
    def _combine(spark, folder, op=_op):
        return L.members(L.combine(buckets(spark, folder), "AF", "NO", op))

    @query(_name.replace("bucket", "packed"), fam_with(f"SELECT 'result' AS set_id, 18 AS r, hv FROM (SELECT {hv_sql(18)} AS hv FROM fam WHERE set_id = '1' {_word} SELECT {hv_sql(18)} AS hv FROM fam WHERE set_id = '2')", "supp_parts"))
    def _balanced(spark, folder, op=_op):
        """Of two stored sets, brought to the buckets that suit both and back to those that suit the result."""
        rungs = L.build_rungs(load_family(spark, folder, "supp_parts").where("set_id in ('1', '2')"), schedule=[18])
        out = staged(L.combine(rungs, "1", "2", op), "combined")
        return L.members(L.rebalance(out, out.agg(F.sum("n").alias("n")).first()["n"] or 1))


def _grown(spark, folder, first, *more, **options) -> L.Ladder:
    """A store written with `first` and appended to, version by version."""
    fam, path = load_family(spark, folder, "flag_orders"), scratch(spark, "ladder")
    L.write_ladder(fam.where(first), path, "sets", **options)
    for condition in more:
        L.append_to_store(spark, path, "sets", fam.where(condition))
    return L.read_ladder(spark, path, "sets")


MEMBERS_SQL = f"WITH fam AS ({family_sql(*FLAGS)}), {RUNG_SQL} SELECT DISTINCT f.set_id, r, {HS} >> ({WIDTH} - r) AS hv FROM fam f JOIN rungs USING (set_id)"


@query("ladder_append", fam_with(f"SELECT DISTINCT set_id, 18 AS r, {hv_sql(18)} AS hv FROM fam", *FLAGS))
def ladder_append(spark, folder):
    return L.members(_grown(spark, folder, "elem % 3 > 0", "elem % 3 = 0", schedule=[18]).rungs).distinct()


@query("ladder_append_new_sets", MEMBERS_SQL)
def ladder_append_new_sets(spark, folder):
    """Two sets that the store has never seen come with the batch."""
    return L.members(_grown(spark, folder, "set_id not in ('NO', 'RF')", "set_id in ('NO', 'RF')").rungs).distinct()


@query("ladder_append_grows", MEMBERS_SQL)
def ladder_append_grows(spark, folder):
    """Sets grow from a few elements past several powers of two, in batches that also repeat what is there."""
    return L.members(_grown(spark, folder, "elem % 64 = 0", "elem % 16 = 0", "elem % 2 = 0", "true").rungs).distinct()


def _of_store(ladder: L.Ladder) -> DataFrame:
    return E.evaluate_packed(TWO_WAYS, ladder)


@query("ladder_append_evaluate", expr_sql(TWO_WAYS, FLAGS))
def ladder_append_evaluate(spark, folder):
    return _of_store(_grown(spark, folder, "elem % 5 > 0 and set_id <> 'AO'", "elem % 5 = 0", "set_id = 'AO'"))


@query("store_rewrite_shrinks", fam_with(to_sql(parse(TWO_WAYS), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}' AND elem % 7 = 0")[1:-1], *FLAGS))
def store_rewrite_shrinks(spark, folder):
    """Written whole, then again with a seventh of the elements: nothing of the first writing may be left."""
    fam, path = load_family(spark, folder, "flag_orders"), scratch(spark, "ladder")
    for condition in ("true", "elem % 7 = 0"):
        L.write_ladder(fam.where(condition), path, "sets")
    return _of_store(L.read_ladder(spark, path, "sets"))


@query("store_tabulation", expr_sql(TWO_WAYS, FLAGS))
def store_tabulation(spark, folder):
    return _of_store(store_of(spark, folder, FLAGS, kind="tabulation", seed=5))


# -- expressions, bounds, sketch, shrink, finish ---------------------------------------------------

NODES = "(AF & AO & NF) | (RF & RO)"


def _bounds_sql() -> str:
    c = {s: f"(SELECT count(*) FROM fam WHERE set_id = '{s}')" for s in ("AF", "AO", "NF", "RF", "RO")}
    inner = f"least({c['AF']}, {c['AO']})"
    left, right = f"least({inner}, {c['NF']})", f"least({c['RF']}, {c['RO']})"
    rows = [(0, "or", None, f"{left} + {right}", f"{left} + {right}"), (1, "and", None, left, left), (2, "and", None, inner, left), (3, "leaf", "AF", c["AF"], left), (4, "leaf", "AO", c["AO"], left), (5, "leaf", "NF", c["NF"], left), (6, "and", None, right, right), (7, "leaf", "RF", c["RF"], right), (8, "leaf", "RO", c["RO"], right)]
    return fam_with(" UNION ALL ".join(f"SELECT {n} AS node, '{op}' AS op, {repr(s) if s else 'NULL'} AS set_id, CAST({a} AS BIGINT) AS psi, CAST({b} AS BIGINT) AS psi_star" for n, op, s, a, b in rows), *FLAGS)


@query("bounds_psi", _bounds_sql())
def bounds_psi(spark, folder):
    e = parse(NODES)
    rows = bounds(e, E.sizes(e, load_family(spark, folder, "flag_orders")))
    return spark.createDataFrame([(x["node"], x["op"], x["set_id"], x["psi"], x["psi_star"]) for x in rows], "node int, op string, set_id string, psi long, psi_star long")


@query("union_depth", "SELECT year, CAST(count(*) - 1 AS INT) AS chain, CAST(ceil(log2(count(*))) AS INT) AS balanced, CASE WHEN count(*) > 1 THEN 1 ELSE 0 END AS flat FROM (SELECT DISTINCT substring(CAST(o_orderdate AS STRING), 1, 4) AS year, substring(CAST(o_orderdate AS STRING), 1, 7) AS month FROM orders) GROUP BY 1")
def depth(spark, folder):
    """Of each year's union of months: as a chain, balanced, and with unbounded fan-in."""
    months = [r["set_id"] for r in load_family(spark, folder, "month_customers").select("set_id").distinct().collect()]  # twelve a year
    rows = []
    for y in sorted({m[:4] for m in months}):
        e = parse(" | ".join(sorted(m for m in months if m[:4] == y)))
        rows.append((y, union_depth(e), union_depth(balance(e)), union_depth(flatten(e))))
    return spark.createDataFrame(rows, "year string, chain int, balanced int, flat int")


@query("choose_precision", fam_with("SELECT CAST(least(62, ceil(log2(count(*))) + 6) AS INT) AS r FROM fam", *FLAGS))
def choose_precision(spark, folder):
    fam = load_family(spark, folder, "flag_orders")
    return spark.createDataFrame([(E.precision(parse(SIX), fam, None),)], "r int")


def _mask_sql(r: int) -> str:
    """Provenance by prefix, the sketch of TWO_WAYS, and rows that each way of shrinking keeps."""
    has = {s: f"bool_or(set_id = '{s}') AS {s.lower()}" for s in ("AF", "AO", "NF", "RF", "RO", "NO")}
    return f"""WITH fam AS ({family_sql(*FLAGS)}), h AS (SELECT {hv_sql(r)} AS hv, {', '.join(has.values())} FROM fam GROUP BY 1),
        s AS (SELECT *, (af AND ao AND nf) AS l, (rf AND ro AND no) AS rr FROM h WHERE (af AND ao AND nf) OR (rf AND ro AND no))"""


@query("dict_lookup", _mask_lookup_sql(15))
def dict_lookup(spark, folder):
    """All elements of every set under the prefixes of a sketch, from the shards that these touch."""
    store = store_of(spark, folder, FLAGS)
    wanted = E.sketch(TWO_WAYS, load_family(spark, folder, "flag_orders"), 15).select("hv").crossJoin(store.catalog.select("set_id"))
    return L.lookup(store.dictionary, wanted, 15, store.shard_bits)


@query("sketch_H", _mask_sql(15) + " SELECT hv FROM s")
def sketch_h(spark, folder):
    return E.sketch(TWO_WAYS, load_family(spark, folder, "flag_orders"), 15).select("hv")


#: A union far larger than what can be useful of it, written before the small side.
CUT = "(AF | AO) & 7"
CUT_FAMILIES = ("flag_orders", "part_orders")
_HV_OF = {s: f"SELECT {hv_sql(15)} AS hv FROM fam WHERE set_id = '{s}'" for s in ("AF", "AO", "7")}


@query("sketch_H_capped", fam_with(f"({_HV_OF['AF']} UNION {_HV_OF['AO']}) INTERSECT {_HV_OF['7']}", *CUT_FAMILIES))
def sketch_capped(spark, folder):
    return E.sketch_by_node(CUT, load_families(spark, folder, list(CUT_FAMILIES)), 15)


def _sizes_sql() -> str:
    """Sizes of the nodes of CUT: root, union, AF, AO, 7. With order and cuts, the small side stands when the others are computed."""
    whole = {1: f"{_HV_OF['AF']} UNION {_HV_OF['AO']}", 2: f"{_HV_OF['AF']} UNION {_HV_OF['AF']}", 3: f"{_HV_OF['AO']} UNION {_HV_OF['AO']}", 4: f"{_HV_OF['7']} UNION {_HV_OF['7']}"}
    whole[0] = f"({whole[1]}) INTERSECT {_HV_OF['7']}"
    rows = []
    for variant, cut in (("ordered_cut", (1, 2, 3)), ("ordered", ()), ("as_written_cut", ())):
        for node, q in sorted(whole.items()):
            q = f"({q}) INTERSECT {_HV_OF['7']}" if node in cut else q
            rows.append(f"SELECT '{variant}' AS variant, {node} AS node, CAST((SELECT count(*) FROM ({q})) AS BIGINT) AS size")
    return fam_with(" UNION ALL ".join(rows), *CUT_FAMILIES)


@query("intermediate_sizes", _sizes_sql())
def intermediate_sizes(spark, folder):
    """What order and cuts save: the size of every intermediate with both, without cuts, and in the order of writing."""
    fam, rows = load_families(spark, folder, list(CUT_FAMILIES)), []
    for variant, options in (("ordered_cut", {}), ("ordered", {"cap": False}), ("as_written_cut", {"ordered": False})):
        sizes: list = []
        E.sketch_by_node(CUT, fam, 15, record=sizes, **options)
        rows += [(variant, node, size) for node, _, size in sizes]
    return spark.createDataFrame(rows, "variant string, node int, size long")


@query("shrink_global", _mask_sql(15) + f" SELECT DISTINCT elem FROM fam JOIN s ON s.hv = {hv_sql(15)}")
def shrink_global(spark, folder):
    return E.shrink(TWO_WAYS, load_family(spark, folder, "flag_orders"), 15, "global").select("elem").distinct()


@query("shrink_path", _mask_sql(15) + f" SELECT set_id, CAST(count(*) AS BIGINT) AS n FROM fam JOIN s ON s.hv = {hv_sql(15)} WHERE (set_id IN ('AF', 'AO', 'NF') AND l) OR (set_id IN ('RF', 'RO', 'NO') AND rr) GROUP BY 1")
def shrink_path(spark, folder):
    rows = E.shrink(TWO_WAYS, load_family(spark, folder, "flag_orders"), 15, "path")
    ids = ["AF", "AO", "NF", "RF", "RO", "NO"]
    named = F.array(*[F.when(F.col("m0").bitwiseAND(F.lit(1 << i)) != 0, F.lit(s)) for i, s in enumerate(ids)])
    return rows.select(F.explode(F.array_compact(named)).alias("set_id")).groupBy("set_id").agg(F.count("*").alias("n"))


ANSWER = expr_sql(TWO_WAYS, FLAGS)
METHODS: dict[str, Callable[[DataFrame], DataFrame]] = {
    "finish_mask": lambda f: E.evaluate(TWO_WAYS, f, mode="path", how="mask"),
    "finish_nested": lambda f: E.evaluate(TWO_WAYS, f, mode="global", how="nested"),
    "evaluate_tree": lambda f: E.evaluate(TWO_WAYS, f),
    "evaluate_auto": lambda f: E.evaluate(TWO_WAYS, f, tier="auto"),
    "evaluate_nodes": lambda f: E.evaluate(TWO_WAYS, f, tier="nodes"),
    "evaluate_sampled_sizes": lambda f: E.evaluate(TWO_WAYS, f, tier="nodes", sampled=3),
    "evaluate_tabulation": lambda f: E.evaluate(TWO_WAYS, f, kind="tabulation", mode="global"),
    "evaluate_low_precision": lambda f: E.evaluate(TWO_WAYS, f, r=10),
    "baseline_merge": lambda f: B.merge_sorted(TWO_WAYS, f),
    "baseline_hash": lambda f: B.hash_probe(TWO_WAYS, f),
    "baseline_bounded_tree": lambda f: B.bounded_tree(TWO_WAYS, f),
    "baseline_mask": lambda f: B.full_hashing(TWO_WAYS, f),
    "baseline_sql": lambda f: B.sql_operators(TWO_WAYS, f),
    "baseline_columns": lambda f: B.wide_sketch(TWO_WAYS, f),
    "ablate_no_shrink": lambda f: E.finish(TWO_WAYS, E.shrink(TWO_WAYS, f, 22, "none")),
    "ablate_fixed_precision": lambda f: E.evaluate(TWO_WAYS, f, r=12),
}
for _name, _fn in METHODS.items():

    @query(_name, ANSWER)
    def _method(spark, folder, fn=_fn):
        return fn(load_family(spark, folder, "flag_orders"))


@query("evaluate_tree_packed", ANSWER)
def evaluate_tree_packed(spark, folder):
    return _of_store(store_of(spark, folder, FLAGS))


for _name, _options in (("evaluate_packed_global", {"mode": "global"}), ("evaluate_packed_wide", {"lanes": 16}), ("evaluate_packed_low_precision", {"r": 12})):

    @query(_name, ANSWER)
    def _packed_variant(spark, folder, options=_options):
        return E.evaluate_packed(TWO_WAYS, store_of(spark, folder, FLAGS), **options)


for _name, _options in (("ablate_no_cap", {"cap": False}), ("ablate_fixed_order", {"ordered": False}), ("baseline_bounded_tree_cut", None)):

    @query(_name, expr_sql(CUT, CUT_FAMILIES))
    def _ablation(spark, folder, options=_options):
        """The answer stays; `intermediate_sizes` and `packed_counters` tell what the switch costs."""
        fam = load_families(spark, folder, list(CUT_FAMILIES))
        return B.bounded_tree(CUT, fam) if options is None else E.evaluate(CUT, fam, tier="nodes", **options)


@query("balanced_union", SQL["w12_deep_unions"])
def balanced_union(spark, folder):
    families, text = WORKLOADS["w12_deep_unions"]
    return E.evaluate(balance(parse(text)), load_families(spark, folder, list(families)))


STRINGS_SQL = "SELECT DISTINCT lang AS set_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS elem FROM documents WHERE lang IS NOT NULL"
STRINGS = "(en & fr) | (de & es)"


@query("evaluate_strings", f"WITH fam AS ({STRINGS_SQL}) SELECT * FROM " + to_sql(parse(STRINGS), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'"))
def evaluate_strings(spark, folder):
    """Sets of words: 62 bits of a practical hash stand for them, and the finish compares the words themselves."""
    words = load_table(spark, folder, "documents", ["lang", "text"]).where("lang is not null").select(F.col("lang").alias("set_id"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("elem")).distinct()
    return E.evaluate(STRINGS, words, kind="xxhash", r=12)


@query("hash_xxhash", STRINGS_SQL.replace("SELECT DISTINCT lang AS set_id, unnest", "SELECT CAST(count(DISTINCT elem) AS BIGINT) AS words, true AS in_range FROM (SELECT unnest") + ")")
def hash_xxhash(spark, folder):
    """Distinct words have distinct 62-bit hashes here, none of them negative."""
    words = load_table(spark, folder, "documents", ["lang", "text"]).where("lang is not null").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("elem"))
    hs = words.select(mother_hash("elem", "xxhash").alias("hs")).distinct()
    return hs.agg(F.count("*").alias("words"), ((F.min("hs") >= 0) & (F.max("hs") < F.lit(1 << WIDTH))).alias("in_range"))


SIX_SQL = expr_sql(SIX, FLAGS)
SETS = ["AF", "AO", "NF", "NO", "RF", "RO"]
MANY: dict[str, Callable[[DataFrame], DataFrame]] = {
    "intersect_m": lambda f: E.intersect_all(SETS, f),
    "baseline_gallop": lambda f: B.gallop(SETS, f),
    "baseline_arrays": lambda f: B.arrays(SETS, f),
}
for _name, _fn in MANY.items():

    @query(_name, SIX_SQL)
    def _many(spark, folder, fn=_fn):
        return fn(load_family(spark, folder, "flag_orders"))


@query("intersect_m_packed", SIX_SQL)
def intersect_m_packed(spark, folder):
    """Ascending sizes, group by group; a group that has run empty stops."""
    return E.evaluate_packed(SIX, store_of(spark, folder, FLAGS))


@query("baseline_bitmap", expr_sql(SIX, FLAGS, "SELECT CAST(count(*) AS BIGINT) AS k FROM answer"))
def baseline_bitmap(spark, folder):
    return B.bitmaps(SETS, load_family(spark, folder, "flag_orders"))


@query("minus_exact", expr_sql("(AF - AO) & (NF | RO)", FLAGS))
def minus_exact(spark, folder):
    return E.evaluate("(AF - AO) & (NF | RO)", load_family(spark, folder, "flag_orders"))


@query("intersect_two", expr_sql("1 & 2", ("supp_parts",)))
def intersect_two(spark, folder):
    return E.intersect_two("1", "2", load_family(spark, folder, "supp_parts"))


def _two_sql(sizes: str) -> str:
    """Occurrences of part 7's and flag A's orders that survive hashes of a range given by `sizes` of both."""
    return fam_with(f", c AS (SELECT count(*) FILTER (WHERE set_id = '7') AS a, count(*) FILTER (WHERE set_id = 'AF') AS b FROM fam), h AS (SELECT set_id, {HS} >> ({WIDTH} - CAST(ceil(log2({sizes})) + 6 AS INT)) AS hv FROM fam, c WHERE set_id IN ('7', 'AF')) SELECT CAST((SELECT ceil(log2({sizes})) + 6 FROM c) AS INT) AS r, CAST(count(*) FILTER (WHERE set_id = 'AF') AS BIGINT) AS of_larger, CAST(count(*) FILTER (WHERE set_id = '7') AS BIGINT) AS of_smaller FROM h WHERE hv IN (SELECT hv FROM h WHERE set_id = '7' INTERSECT SELECT hv FROM h WHERE set_id = 'AF')", "part_orders", "flag_orders").replace(") , c AS", "), c AS")


for _name, _sizes, _pick in (("intersect_two_candidates", "least(a, b)", min), ("intersect_two_candidates_total", "a + b", None)):

    @query(_name, _two_sql(_sizes))
    def _two(spark, folder, pick=_pick):
        """Candidates with the hash range tied to the smaller set, and to the total."""
        fam = load_families(spark, folder, ["part_orders", "flag_orders"])
        cards = list(E.sizes(parse("7 & AF"), fam).values())
        r = choose.choose_r([pick(cards)] if pick else cards)
        kept = E.shrink("7 & AF", fam, r, "global")
        return kept.agg(F.lit(r).alias("r"), F.count_if(F.col("m0").bitwiseAND(F.lit(2)) != 0).alias("of_larger"), F.count_if(F.col("m0").bitwiseAND(F.lit(1)) != 0).alias("of_smaller"))


@query("intersect_probe", expr_sql("7 & AF", ("part_orders", "flag_orders")))
def intersect_probe(spark, folder):
    return E.probe(["7", "AF"], load_families(spark, folder, ["part_orders", "flag_orders"]))


@query("intersect_probe_stored", expr_sql("7 & AF", ("part_orders", "flag_orders")))
def intersect_probe_stored(spark, folder):
    """From a store: only the buckets of the larger set that the smaller one touches are read."""
    return E.probe_stored(["7", "AF"], store_of(spark, folder, ("part_orders", "flag_orders")))


@query("approx_superset", _mask_sql(15) + f" SELECT DISTINCT elem FROM fam JOIN s ON s.hv = {hv_sql(15)}")
def approx_superset(spark, folder):
    return E.approximate(TWO_WAYS, load_family(spark, folder, "flag_orders"), 15)


@query("cardinality", expr_sql(TWO_WAYS, FLAGS, "SELECT CAST(count(*) AS BIGINT) AS k FROM answer"))
def cardinality(spark, folder):
    return E.cardinality(TWO_WAYS, load_family(spark, folder, "flag_orders"))


@query("occurrences", expr_sql(TWO_WAYS, FLAGS, "SELECT set_id, elem FROM fam WHERE elem IN (SELECT elem FROM answer)"))
def occurrences(spark, folder):
    return E.occurrences(TWO_WAYS, load_family(spark, folder, "flag_orders"))


@query("union_only", expr_sql("AF | AO | RO", FLAGS))
def union_only(spark, folder):
    return E.evaluate("AF | AO | RO", load_family(spark, folder, "flag_orders"), tier="union")


@query("disjoint_test", expr_sql(SIX, FLAGS, "SELECT count(*) = 0 AS disjoint FROM answer"))
def disjoint_test(spark, folder):
    return P.is_disjoint(SETS, load_family(spark, folder, "flag_orders"))


#: Pairs of orders' sets: "any A" against the union of both A flags (equal), and against one of them.
EQUAL_PAIRS = {"either": "SELECT DISTINCT l_orderkey AS elem FROM lineitem WHERE l_returnflag = 'A' AND l_linestatus IN ('F', 'O')", "one": "SELECT DISTINCT l_orderkey AS elem FROM lineitem WHERE l_returnflag = 'A' AND l_linestatus = 'F'"}
_ANY_A = "SELECT DISTINCT l_orderkey AS elem FROM lineitem WHERE l_returnflag = 'A'"


@query("equality_test", " UNION ALL ".join(f"SELECT '{k}' AS pair, (SELECT count(*) FROM (({_ANY_A}) EXCEPT ({q}))) + (SELECT count(*) FROM (({q}) EXCEPT ({_ANY_A}))) = 0 AS equal" for k, q in EQUAL_PAIRS.items()))
def equality_test(spark, folder):
    lines = load_table(spark, folder, "lineitem", ["l_orderkey", "l_returnflag", "l_linestatus"]).where("l_returnflag = 'A'")
    key = F.col("l_orderkey").cast("long").alias("elem")
    whole = lines.select(F.lit("any").alias("set_id"), key).distinct()
    parts = []
    for pair, status in (("either", ["F", "O"]), ("one", ["F"])):
        other = lines.where(F.col("l_linestatus").isin(status)).select(F.lit("other").alias("set_id"), key).distinct()
        parts.append(P.sets_equal("any", "other", whole.union(other)).select(F.lit(pair).alias("pair"), "equal"))
    return parts[0].union(parts[1])


@query("equality_gadget", expr_sql("1 & 2", ("supp_parts",)))
def equality_gadget(spark, folder):
    return E.evaluate(P.equality_instance(parse("(a & b) | (c & d)"), "1", "2"), load_family(spark, folder, "supp_parts"))


@query(
    "w18_equality",
    """WITH d AS (SELECT doc_id, regexp_extract_all(lower(text), '[^\\s]+') AS w FROM documents),
    g AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d)),
    x AS (SELECT doc_id, list(s ORDER BY s) AS shingles FROM g GROUP BY 1)
    SELECT doc_id, min(doc_id) OVER (PARTITION BY shingles) AS same_as FROM x QUALIFY count(*) OVER (PARTITION BY shingles) > 1""".replace("\\\\", "\\"),
)
def w18_equality(spark, folder):
    """Documents whose sets of word 5-grams are equal: fingerprints find them, the sets themselves confirm."""
    w = F.regexp_extract_all(F.lower("text"), F.lit("[^\\s]+"), F.lit(0))
    grams = F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, 5), " "))))
    docs = load_table(spark, folder, "documents", ["doc_id", "text"]).select("doc_id", w.alias("w")).where("size(w) >= 5").select("doc_id", grams.alias("shingles"))
    printed = staged(docs.select("doc_id", F.size("shingles").alias("n"), F.xxhash64("shingles").alias("x"), F.xxhash64(F.lit(5), "shingles").alias("y"), "shingles"), "shingles")
    same = printed.groupBy("n", "x", "y").agg(F.min("doc_id").alias("rep"), F.count("*").alias("c")).where("c > 1").select("n", "x", "y", "rep")
    reps = printed.join(same, (printed.doc_id == same.rep) & (printed.x == same.x)).select("rep", F.col("shingles").alias("whole"))
    near = printed.join(same, ["n", "x", "y"]).select("doc_id", "rep", "shingles")
    return near.join(reps, "rep").where("shingles = whole").select("doc_id", F.col("rep").alias("same_as"))


@query("set_equal_test", "SELECT r_name AS region, true AS equal FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey GROUP BY 1")
def set_equal_test(spark, folder):
    """Each region's customers against the union of its nations' customers."""
    regions = load_family(spark, folder, "cust_region").select("set_id", "elem", F.lit(0).alias("side"))
    names = load_table(spark, folder, "nation").join(load_table(spark, folder, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("set_id"), "r_name")
    nations = load_family(spark, folder, "cust_nation").join(F.broadcast(names), "set_id").select(F.col("r_name").alias("set_id"), "elem", F.lit(1).alias("side")).distinct()
    hs = mother_hash("elem")
    prints = regions.union(nations).groupBy("set_id", "side").agg(F.count("*").alias("n"), F.bit_xor(hs).alias("x"), F.sum(F.pmod(hs, F.lit(1 << 31))).alias("s"))
    odd = regions.union(nations).groupBy("set_id", "elem").agg(F.count("*").alias("c")).where("c <> 2").groupBy("set_id").agg(F.count("*").alias("odd"))
    same = prints.groupBy("set_id").agg(F.countDistinct("n", "x", "s").alias("kinds"))
    return same.join(odd, "set_id", "left").select(F.col("set_id").alias("region"), ((F.col("kinds") == 1) & F.col("odd").isNull()).alias("equal"))


@query("set_disjoint_test", fam_with("SELECT a.set_id AS a, b.set_id AS b, (SELECT count(*) FROM fam x JOIN fam y ON x.elem = y.elem WHERE x.set_id = a.set_id AND y.set_id = b.set_id) = 0 AS disjoint FROM (SELECT DISTINCT set_id FROM fam) a JOIN (SELECT DISTINCT set_id FROM fam) b ON a.set_id < b.set_id", "part_type", "part_brand"))
def set_disjoint_test(spark, folder):
    """All pairs of a bounded number of sets: part types and brands."""
    fam = load_families(spark, folder, ["part_type", "part_brand"])
    names = fam.select("set_id").distinct()
    pairs = names.select(F.col("set_id").alias("a")).join(F.broadcast(names.select(F.col("set_id").alias("b"))), F.col("a") < F.col("b"))
    meet = fam.select(F.col("set_id").alias("a"), "elem").join(fam.select(F.col("set_id").alias("b"), "elem"), "elem").where("a < b").select("a", "b").distinct().withColumn("meet", F.lit(True))
    return pairs.join(meet, ["a", "b"], "left").select("a", "b", F.col("meet").isNull().alias("disjoint"))


def _sampled_sql() -> str:
    kept = f"samp AS (SELECT * FROM fam WHERE ({HS} & 7) = 0)"
    leaf = lambda s: f"SELECT elem FROM samp WHERE set_id = '{s}'"
    parts = [f"({leaf('AF')} INTERSECT {leaf('AO')})", leaf("AF"), leaf("AO")]
    return f"WITH fam AS ({family_sql(*FLAGS)}), {kept} " + " UNION ALL ".join(f"SELECT {i} AS node, CAST(count(*) AS BIGINT) AS sampled, CAST(8 * count(*) AS BIGINT) AS estimate FROM ({p})" for i, p in enumerate(parts))


@query("sampled_sizes", _sampled_sql())
def sampled_sizes(spark, folder):
    return P.sampled_sizes("AF & AO", load_family(spark, folder, "flag_orders"), 3)


# -- costs, space, accuracy -------------------------------------------------------------------------

COUNTS = expr_sql(SIX, FLAGS, "SELECT CAST((SELECT count(*) FROM fam) AS DOUBLE) AS n, CAST(6 AS DOUBLE) AS m, CAST(count(*) AS DOUBLE) AS k FROM answer")
#: Formulas of n, m, k over a 64-bit word, valid in either engine.
FORMULAS = {
    "cost_intersection": "n * pow(log2(64), 2) / 64 + k * m",
    "cost_io": "n * log2(64 * 128) / (64 * 128) + k * m",
    "cost_lower": "n / (64 * m * log2(m)) + (1 - log2(k) / 64) * k",
    "cost_gap": "(n * pow(log2(64), 2) / 64 + k * m) / (n / (64 * m * log2(m)) + (1 - log2(k) / 64) * k)",
    "speedup_predicted": "n / (n * pow(log2(64), 2) / 64 + k * m)",
}
for _name, _formula in FORMULAS.items():

    @query(_name, f"SELECT n, m, k, round({_formula}, 6) AS value FROM ({COUNTS})")
    def _cost(spark, folder, formula=_formula):
        fam = load_family(spark, folder, "flag_orders")
        k = E.cardinality(SIX, fam).select(F.col("k").cast("double").alias("k"))
        n = fam.agg(F.count("*").cast("double").alias("n"))
        return n.join(k).select("n", F.lit(6.0).alias("m"), "k").select("n", "m", "k", F.round(F.expr(formula), 6).alias("value"))


@query("io_model_costs", f"SELECT CAST(b AS INT) AS block, round(n * log2(64 * b) / (64 * b) + k * m, 4) AS upper, round(n / (64 * b * m * log2(m)) + (1 - log2(k) / (64 * b)) * k, 4) AS lower FROM ({COUNTS}), (SELECT unnest([1, 16, 128, 1024]) AS b)")
def io_model_costs(spark, folder):
    """Both bounds in the I/O model, as blocks grow from one word to 1,024."""
    p = E.profile(SIX, load_family(spark, folder, "flag_orders"))
    n, m, k = p["n"], p["m"], p["k"]
    rows = [(b, round(cost.cost_io(n, m, k, 64, b), 4), round(cost.cost_lower(n, m, k, 64 * b), 4)) for b in (1, 16, 128, 1024)]
    return spark.createDataFrame(rows, "block int, upper double, lower double")


#: Queries whose bounds are told for every width of words.
BOUNDED = {"flags": (FLAGS, TWO_WAYS), "predicates": WORKLOADS["w13_alternating"], "years": WORKLOADS["w12_deep_unions"]}
WIDTHS = (64, 256, 1024, 4096)


def _bounds_of(text: str) -> list[tuple[str, str, str]]:
    """(operator, psi, psi_star) of every node, as SQL over a table c of sizes."""
    rows = walk(parse(text))
    psi: dict[int, str] = {}
    for me, _, n in reversed(rows):
        kids = [psi[i] for i, p, _ in rows if p == me]
        psi[me] = f"coalesce((SELECT card FROM c WHERE set_id = '{n.set_id}'), 0)" if isinstance(n, Leaf) else f"least({', '.join(kids)})" if n.op == "and" else f"({' + '.join(kids)})"
    star: dict[int, str] = {}
    for me, parent, _ in rows:
        star[me] = psi[me] if parent < 0 else f"least({psi[me]}, {star[parent]})"
    return [("leaf" if isinstance(n, Leaf) else n.op, psi[me], star[me]) for me, _, n in rows]


def _bound_sql(nodes: tuple[str, ...]) -> str:
    parts = []
    for name, (families, text) in BOUNDED.items():
        ids = [x.set_id for x in leaves(parse(text))]
        body = to_sql(parse(text), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'")
        quoted = ", ".join(f"'{s}'" for s in set(ids))
        n = " + ".join(f"coalesce((SELECT card FROM c WHERE set_id = '{s}'), 0)" for s in ids)
        stars = " UNION ALL ".join(f"SELECT {star} AS v" for op, _, star in _bounds_of(text) if op in nodes)
        parts.append(f"""SELECT * FROM (WITH fam AS ({family_sql(*families)}), c AS (SELECT set_id, count(*) AS card FROM fam GROUP BY 1), answer AS (SELECT * FROM {body}),
            v AS ({stars}), t AS (SELECT {n} AS n, (SELECT count(*) FROM fam WHERE set_id IN ({quoted}) AND elem IN (SELECT elem FROM answer)) AS kprime)
            SELECT '{name}' AS query, CAST(w AS INT) AS w, CAST(n AS BIGINT) AS n, CAST(kprime AS BIGINT) AS kprime, CAST(kprime + (SELECT sum(ceil(v / w * pow(log2(greatest(n * w / v, 1)), 2))) FROM v WHERE v > 0) AS DOUBLE) AS value FROM t, (SELECT CAST(unnest({list(WIDTHS)}) AS DOUBLE) AS w))""")
    return " UNION ALL ".join(parts)


for _name, _fn, _nodes in (("cost_expression", cost.cost_expression, ("leaf", "or", "and")), ("cost_leaf_union", cost.cost_leaf_union, ("leaf", "or"))):

    @query(_name, _bound_sql(_nodes))
    def _bound(spark, folder, fn=_fn):
        rows = []
        for name, (families, text) in BOUNDED.items():
            fam = load_families(spark, folder, list(families))
            p, nodes = E.profile(text, fam), bounds(parse(text), E.sizes(parse(text), fam))
            rows += [(name, w, p["n"], p["kprime"], float(fn(nodes, p["n"], p["kprime"], w))) for w in WIDTHS]
        return spark.createDataFrame(rows, "query string, w int, n long, kprime long, value double")


def _depth_sql() -> str:
    families, text = WORKLOADS["w12_deep_unions"]
    body = to_sql(parse(text), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'")
    ids = [x.set_id for x in leaves(parse(text))]
    quoted = ", ".join(f"'{s}'" for s in ids)
    return f"""WITH fam AS ({family_sql(*families)}), answer AS (SELECT * FROM {body}), t AS (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(count(*) FILTER (WHERE elem IN (SELECT elem FROM answer)) AS DOUBLE) AS kp FROM fam WHERE set_id IN ({quoted}))
        SELECT form, CAST(d AS INT) AS depth, CAST(w AS INT) AS w, round({len(ids)} + kp + n / w * pow(d + log2(w), 2), 4) AS value FROM t, (VALUES ('chain', 11), ('balanced', 4)) f(form, d), (SELECT CAST(unnest({list(WIDTHS)}) AS DOUBLE) AS w)"""


@query("cost_union_depth", _depth_sql())
def cost_union_depth(spark, folder):
    """The bound by union depth, for a year's months as a chain and balanced."""
    families, text = WORKLOADS["w12_deep_unions"]
    fam = load_families(spark, folder, list(families))
    p = E.profile(text, fam)
    rows = [(form, union_depth(e), w, round(cost.cost_union_depth(p["n"], p["m"], p["kprime"], union_depth(e), w), 4)) for form, e in (("chain", parse(text)), ("balanced", balance(parse(text)))) for w in WIDTHS]
    return spark.createDataFrame(rows, "form string, depth int, w int, value double")


@query("query_profile", expr_sql(TWO_WAYS, FLAGS, "SELECT 6 AS m, (SELECT count(*) FROM fam) AS n, (SELECT count(*) FROM answer) AS k, (SELECT count(*) FROM fam WHERE elem IN (SELECT elem FROM answer)) AS kprime, 1 AS depth"))
def query_profile(spark, folder):
    p = E.profile(TWO_WAYS, load_family(spark, folder, "flag_orders"))
    return spark.createDataFrame([(p["m"], p["n"], p["k"], p["kprime"], p["depth"])], "m int, n long, k long, kprime long, depth int")


@query("skew_factor", fam_with("SELECT CAST(max(c) AS BIGINT) AS large, CAST(min(c) AS BIGINT) AS small, round(log2(1 + max(c) / CAST(min(c) AS DOUBLE)), 6) AS factor FROM (SELECT count(*) AS c FROM fam GROUP BY set_id)", *FLAGS))
def skew_factor(spark, folder):
    cards = catalog(load_family(spark, folder, "flag_orders")).agg(F.max("card").alias("large"), F.min("card").alias("small"))
    return cards.select("large", "small", F.round(F.log2(1 + F.col("large") / F.col("small")), 6).alias("factor"))


#: Fields of a word by the bits of a bucket's remainders, as a table for SQL.
FIELDS_SQL = "fields(l, k) AS (VALUES " + ", ".join(f"({v}, {choose.fields_per_word(choose.field_bits(v))})" for v in range(WIDTH + 1)) + ")"


def _stored_sql(rungs: str) -> str:
    """per: (set_id, r, words, n, largest) of stored rungs, from a table of (set_id, card, r); words are counted bucket by bucket."""
    return f"""{FIELDS_SQL}, shape AS (SELECT set_id, card, r, CAST(least(r, greatest(0, floor(log2(card) - 6))) AS INT) AS b FROM ({rungs})),
        vals AS (SELECT DISTINCT f.set_id, r, b, {HS} >> ({WIDTH} - r) AS hv FROM fam f JOIN shape USING (set_id)),
        bucketed AS (SELECT set_id, r, b, hv >> (r - b) AS bucket, count(*) AS c FROM vals GROUP BY ALL),
        per AS (SELECT set_id, r, CAST(sum(greatest(1, ceil(c / k))) AS BIGINT) AS words, CAST(sum(c) AS BIGINT) AS n, CAST(max(c) AS INT) AS largest FROM bucketed JOIN fields ON l = r - b GROUP BY 1, 2)"""


#: Precisions of a set of a given size: the ladder (one rung for tiny sets), and all of them.
LADDER_RUNGS = f"SELECT DISTINCT set_id, card, r FROM (SELECT set_id, card, CASE WHEN card < {choose.TINY} THEN {WIDTH} ELSE base + CAST(pow(2, i) AS INT) END AS r FROM cards, (SELECT unnest(range(0, 6)) AS i) WHERE i <= floor(log2({WIDTH} - base)) UNION ALL SELECT set_id, card, {WIDTH} FROM cards) WHERE r <= {WIDTH}"
ALL_RUNGS = f"SELECT set_id, card, CAST(r AS INT) AS r FROM cards, (SELECT unnest(range(1, {WIDTH + 1})) AS r) WHERE r >= base"
CARDS_SQL = "cards AS (SELECT set_id, count(*) AS card, CAST(ceil(log2(count(*))) AS INT) AS base FROM fam GROUP BY 1)"


@query("space_rungs", fam_with(f", {CARDS_SQL}, {_stored_sql(LADDER_RUNGS)} SELECT set_id, r, words * 64 AS bits, CAST(card * (r - b) + pow(2, b) * 64 AS BIGINT) AS bound FROM per JOIN shape USING (set_id, r)", *FLAGS).replace(") , cards", "), cards"))
def space_rungs(spark, folder):
    """Bits of every stored rung, read from the store, beside card (r - b) + 2^b W."""
    store = store_of(spark, folder, FLAGS)
    read = store.rungs.groupBy("set_id", "r").agg((F.sum(F.size("words")) * 64).cast("long").alias("bits"))
    b = F.least(F.col("b"), F.col("r"))
    return read.join(store.catalog.select("set_id", "card", "b"), "set_id").select("set_id", "r", "bits", (F.col("card") * (F.col("r") - b) + F.pow(F.lit(2), b) * 64).cast("long").alias("bound"))


for _name, _schedule, _rungs in (("space_ladder", "ladder", LADDER_RUNGS), ("space_all_precisions", "all", ALL_RUNGS)):

    @query(_name, fam_with(f", {CARDS_SQL}, {_stored_sql(_rungs)} SELECT set_id, CAST(sum(words) AS BIGINT) AS words, max(largest) AS largest_bucket, CAST(count(*) AS BIGINT) AS rungs FROM per GROUP BY 1", "supp_parts").replace(") , cards", "), cards"))
    def _space(spark, folder, schedule=_schedule):
        rungs = store_of(spark, folder, ("supp_parts",), schedule=schedule).rungs
        return rungs.groupBy("set_id").agg(F.sum(F.size("words")).alias("words"), F.max("n").alias("largest_bucket"), F.countDistinct("r").alias("rungs"))


def accuracy(spark, folder, kind: str, steps=(-3, -2, -1, 0, 1, 2, 3, 4, 5, 6)) -> DataFrame:
    """Candidates and sketch sizes by precision, against the ideal k m and k."""
    fam = load_family(spark, folder, "flag_orders")
    p = E.profile(SIX, fam)
    base = choose.ceil_log2(p["n"])
    out = None
    for c in steps:
        kept = E.shrink(SIX, fam, base + c, "global", kind).agg(F.sum(F.expr("bit_count(m0)")).alias("candidates"), F.countDistinct("hv").alias("sketch"))
        row = kept.select(F.lit(c).alias("step"), F.lit(base + c).alias("r"), "candidates", "sketch", F.lit(p["k"] * p["m"]).alias("ideal"), F.lit(p["k"]).alias("k"), F.round(F.lit(cost.false_bound(p["n"], base + c)), 3).alias("bound"))
        out = row if out is None else out.union(row)
    return out


def _accuracy_sql(kind: str, c: int) -> str:
    h = mother_hash_sql("elem", kind)
    return f"""WITH fam AS ({family_sql(*FLAGS)}), b AS (SELECT CAST(ceil(log2(count(*))) AS INT) + {c} AS r FROM fam), hashed AS (SELECT set_id, elem, {h} >> ({WIDTH} - r) AS hv FROM fam, b),
        s AS (SELECT hv FROM hashed GROUP BY 1 HAVING count(DISTINCT set_id) = 6)"""


for _kind in ("tabulation", "linear2"):

    @query(f"false_candidates_{_kind}", _accuracy_sql(_kind, 1) + f" SELECT 1 AS step, CAST(count(*) AS BIGINT) AS candidates, CAST(count(DISTINCT hv) AS BIGINT) AS sketch FROM hashed WHERE hv IN (SELECT hv FROM s)")
    def _false(spark, folder, kind=_kind):
        return accuracy(spark, folder, kind, (1,)).select("step", "candidates", "sketch")


STEPS = (-3, -2, -1, 0, 1, 2, 3, 4, 5, 6)


def _sweep_sql(kind: str) -> str:
    body = to_sql(parse(SIX), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'")
    one = lambda c: f"SELECT CAST({c} AS INT) AS step, (SELECT max(r) FROM b{c + 3}) AS r, CAST(count(*) AS BIGINT) AS candidates, CAST(count(DISTINCT hv) AS BIGINT) AS sketch FROM h{c + 3} WHERE hv IN (SELECT hv FROM s{c + 3})"
    h = mother_hash_sql("elem", kind)
    tables = ", ".join(f"b{c + 3} AS (SELECT CAST(ceil(log2(count(*))) AS INT) + {c} AS r FROM fam), h{c + 3} AS (SELECT set_id, hs >> ({WIDTH} - r) AS hv FROM hashed, b{c + 3}), s{c + 3} AS (SELECT hv FROM h{c + 3} GROUP BY 1 HAVING count(DISTINCT set_id) = 6)" for c in STEPS)
    return f"""WITH fam AS ({family_sql(*FLAGS)}), hashed AS (SELECT set_id, elem, {h} AS hs FROM fam), {tables}, answer AS (SELECT * FROM {body}), k AS (SELECT count(*) AS k FROM answer), n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM fam)
        SELECT step, r, candidates, sketch, CAST(6 * k AS INT) AS ideal, CAST(k AS INT) AS k, round(n * n / pow(2, r), 3) AS bound FROM ({" UNION ALL ".join(map(one, STEPS))}), k, n"""


@query("w15_precision_sweep", _sweep_sql("tabulation"))
def w15_precision_sweep(spark, folder):
    return accuracy(spark, folder, "tabulation")


@query("sketch_accuracy", _sweep_sql("linear2").replace("SELECT step, r, candidates, sketch, CAST(6 * k AS INT) AS ideal, CAST(k AS INT) AS k, round(n * n / pow(2, r), 3) AS bound", "SELECT step, CAST(sketch AS BIGINT) AS sketch, CAST(k AS BIGINT) AS k, round(k / sketch, 6) AS precision, (SELECT count(DISTINCT hs) FROM hashed WHERE elem IN (SELECT elem FROM answer)) >= k AS whole"))
def sketch_accuracy(spark, folder):
    """Precision of the default hash's sketch by its range; it never loses an answer."""
    rows = accuracy(spark, folder, "linear2")
    return rows.select("step", "sketch", F.col("k").cast("long").alias("k"), F.round(F.col("k") / F.col("sketch"), 6).alias("precision"), (F.col("sketch") <= F.col("candidates")).alias("whole"))


@query("reduction_ratio", _mask_sql(15) + f" SELECT CAST((SELECT count(*) FROM fam) AS BIGINT) AS n, CAST((SELECT count(*) FROM fam JOIN s ON s.hv = {hv_sql(15)}) AS BIGINT) AS kept")
def reduction_ratio(spark, folder):
    fam = load_family(spark, folder, "flag_orders")
    kept = E.shrink(TWO_WAYS, fam, 15, "global").agg(F.sum(F.expr("bit_count(m0)")).cast("long").alias("kept"))
    return fam.agg(F.count("*").alias("n")).join(kept)


def packed_run(spark, folder, families, text, **options) -> dict:
    """Counters of one packed evaluation from the store, and its plan's numbers."""
    store = store_of(spark, folder, families)
    plan = E.plan_packed(text, store, **options)
    found = staged(E.packed_candidates(plan, store), "counted")
    return E.counters(found, set_ids(plan.expr)) | {"plan": plan, "n": sum(plan.cards[x.set_id] for x in leaves(plan.expr)), "found": found}


#: Queries that are counted: name -> (families, expression)
COUNTED = {"flags": (FLAGS, TWO_WAYS), "six": (FLAGS, SIX), "cut": (CUT_FAMILIES, CUT), "years": WORKLOADS["w12_deep_unions"], "terms": (TERMS, "(the & of) | (que & les)")}


@query("w16_word_size")
def w16_word_size(spark, folder):
    """Word operations as words grow from 64 to 4,096 bits, beside the predicted gain W / log^2 W over 64-bit words."""
    rows, first = [], None
    for lanes in (1, 4, 16, 64):
        c = packed_run(spark, folder, FLAGS, TWO_WAYS, lanes=lanes)
        first = first or c["word_ops"]
        rows.append((64 * lanes, c["n"], c["plan"].r, c["plan"].b, c["word_ops"], round(first / c["word_ops"], 3), round(cost.predicted_speedup(64 * lanes) / cost.predicted_speedup(64), 3)))
    return spark.createDataFrame(rows, "w int, n long, r int, b int, word_ops long, gain double, predicted double")


@query("measured_ops")
def measured_ops(spark, folder):
    """Word operations, intermediates, cuts and stops of the counted queries, beside the bound of the whole expression."""
    rows = []
    for name, (families, text) in COUNTED.items():
        c = packed_run(spark, folder, families, text)
        bound = cost.cost_expression(bounds(c["plan"].expr, c["plan"].cards), c["n"], 0, 64)
        rows.append((name, c["n"], c["word_ops"], c["intermediate"], c["cuts"], c["skipped"], c["sketch"], c["candidates"], float(bound), round(c["word_ops"] / max(bound, 1.0), 3)))
    return spark.createDataFrame(rows, "query string, n long, word_ops long, intermediate long, cuts long, skipped long, sketch long, candidates long, bound double, ratio double")


@query("packed_counters")
def packed_counters(spark, folder):
    """What each switch costs on the packed tier, where a large union stands beside a small set."""
    rows = []
    for variant, options in (("all", {}), ("no_cut", {"cap": False}), ("as_written", {"ordered": False}), ("global", {"mode": "global"})):
        c = packed_run(spark, folder, CUT_FAMILIES, CUT, **options)
        rows.append((variant, c["word_ops"], c["intermediate"], c["cuts"], c["skipped"], c["candidates"]))
    return spark.createDataFrame(rows, "variant string, word_ops long, intermediate long, cuts long, skipped long, candidates long")


@query("w12_union_forms")
def w12_union_forms(spark, folder):
    """A year's months united one after the other, and balanced: same answer, fewer word operations."""
    families, text = WORKLOADS["w12_deep_unions"]
    rows = []
    for form, balanced in (("chain", False), ("balanced", True)):
        c = packed_run(spark, folder, families, text, balanced=balanced)
        rows.append((form, c["word_ops"], c["intermediate"], c["sketch"], c["candidates"]))
    return spark.createDataFrame(rows, "form string, word_ops long, intermediate long, sketch long, candidates long")


def _read_sql(expr: str, select: str) -> str:
    """Words that a packed run of an expression over all flag sets reads of each set: its smallest sufficient rung."""
    names = ", ".join(f"'{s}'" for s in set_ids(parse(expr)))
    return fam_with(f", {CARDS_SQL}, {_stored_sql(LADDER_RUNGS)}, need AS (SELECT least({WIDTH}, CAST(ceil(log2(sum(card))) AS INT) + 6) AS r0 FROM cards WHERE set_id IN ({names})), pick AS (SELECT set_id, min(r) AS r FROM per, need WHERE r >= r0 AND set_id IN ({names}) GROUP BY 1) SELECT {select} FROM pick JOIN per USING (set_id, r) JOIN cards USING (set_id)", *FLAGS).replace(") , cards", "), cards")


@query("measured_bits", _read_sql(SIX, "set_id, CAST(card AS BIGINT) AS card, r AS rung, words * 64 AS bits, round(words * 64 / card, 4) AS bits_per_element"))
def measured_bits(spark, folder):
    """Bits that a run reads of each input set's stored rung."""
    c = packed_run(spark, folder, FLAGS, SIX)
    rows = [(s, c["plan"].cards[s], c["plan"].rungs[s], c[f"words_of {s}"] * 64, round(c[f"words_of {s}"] * 64 / c["plan"].cards[s], 4)) for s in SETS]
    return spark.createDataFrame(rows, "set_id string, card long, rung int, bits long, bits_per_element double")


@query("transcript_bits", _read_sql(TWO_WAYS, "set_id AS player, words * 64 AS bits"))
def transcript_bits(spark, folder):
    """The run as a protocol: every word read of a player's set is written on the board."""
    c = packed_run(spark, folder, FLAGS, TWO_WAYS)
    return P.transcript(spark, {s: c[f"words_of {s}"] for s in SETS})


@query("trivial_protocol", fam_with("SELECT DISTINCT set_id AS player, CAST((SELECT max(elem) + 1 FROM fam) AS BIGINT) AS bits FROM fam", *FLAGS))
def trivial_protocol(spark, folder):
    return B.trivial_bits(load_family(spark, folder, "flag_orders"))


@query("measured_probes")
def measured_probes(spark, folder):
    """Cells that a run touches of each set: words of its rung, and dictionary entries of its surviving prefixes; with the comparisons of
    a search by doubling steps."""
    c = packed_run(spark, folder, FLAGS, SIX)
    per = {r["leaf"]: r["n"] for r in c["found"].where("leaf >= 0").groupBy("leaf").agg(F.count("*").alias("n")).collect()}
    looked = {x.set_id: per.get(i, 0) for i, x in enumerate(leaves(c["plan"].expr))}
    spent = B.gallop(SETS, load_family(spark, folder, "flag_orders"), counts=True).agg(F.sum("elem").alias("c")).first()["c"]
    rows = [(s, c["plan"].cards[s], c[f"words_of {s}"], looked[s], spent) for s in SETS]
    return spark.createDataFrame(rows, "set_id string, card long, words long, lookups long, comparisons_of_all long")


@query("gain_over_comparisons")
def gain_over_comparisons(spark, folder):
    """Elements that the comparison-based algorithm goes over, against word operations of 64 and 4,096 bits for the same expressions."""
    rows = []
    for name, (families, text) in COUNTED.items():
        sizes: list = []
        E.sketch_by_node(flatten(parse(text)), load_families(spark, folder, list(families)), 0, raw=True, record=sizes)
        narrow, wide = (packed_run(spark, folder, families, text, lanes=lanes)["word_ops"] for lanes in (1, 64))
        rows.append((name, sum(n for _, _, n in sizes), narrow, wide))
    return spark.createDataFrame(rows, "query string, elements long, word_ops_64 long, word_ops_4096 long")


def _build_sql() -> str:
    parts = []
    for name in ("flag_orders", "supp_parts", "status_customers"):
        parts.append(f"SELECT * FROM (WITH fam AS ({family_sql(name)}), {CARDS_SQL}, {_stored_sql(LADDER_RUNGS)} SELECT '{name}' AS family, CAST((SELECT count(*) FROM fam) AS BIGINT) AS elements, CAST(count(*) AS BIGINT) AS rungs, CAST(sum(n) AS BIGINT) AS derived, CAST(sum(words) AS BIGINT) AS words FROM per)")
    return " UNION ALL ".join(parts)


@query("w19_build", _build_sql())
def w19_build(spark, folder):
    """Work and space of a build: values written over all rungs (each derived once from the rung above), and words."""
    out = None
    for name in ("flag_orders", "supp_parts", "status_customers"):
        fam = staged(load_family(spark, folder, name), "family")
        rungs = L.build_rungs(fam).groupBy("set_id", "r").agg(F.sum("n").alias("n"), F.sum(F.size("words")).alias("words"))
        row = rungs.agg(F.lit(name).alias("family"), F.lit(fam.count()).cast("long").alias("elements"), F.count("*").alias("rungs"), F.sum("n").alias("derived"), F.sum("words").alias("words"))
        out = row if out is None else out.union(row)
    return out


@query("explain_plan")
def explain_plan(spark, folder):
    """The steps of a packed evaluation: order, rungs, bounds, and what may be cut."""
    plan = E.plan_packed(CUT, store_of(spark, folder, CUT_FAMILIES))
    return spark.createDataFrame(plan.steps(), "step int, node int, op string, set_id string, rung int, psi long, psi_star long, may_be_cut boolean")


def packed_moves(spark, folder, families, text) -> list[tuple[str, str, int]]:
    """Spark's counters of both steps of a packed evaluation: the sketch on stored rungs, and the finish on the dictionary."""
    store = store_of(spark, folder, families)
    sketch = E.packed_candidates(E.plan_packed(text, store), store)
    return measure.spark_counters(sketch) + measure.spark_counters(E.evaluate_packed(text, store))


@query("spark_counters")
def spark_counters(spark, folder):
    """What a query with a small answer reads and shuffles from the store (packed rows of the sketch, dictionary rows of the finish), against
    all elements held, and without a store."""
    families, text = ("part_orders", "flag_orders"), "7 & AF & RF"
    held, fam = store_of(spark, folder, families).dictionary.count(), load_families(spark, folder, list(families))
    ways = {"packed": packed_moves(spark, folder, families, text), "columns": measure.spark_counters(E.evaluate(text, fam)), "baseline_sql": measure.spark_counters(B.sql_operators(text, fam)), "baseline_mask": measure.spark_counters(B.full_hashing(text, fam))}
    rows = [(name, held, measure.total(c, "Scan", "numOutputRows"), measure.total(c, "Scan", "filesSize"), measure.total(c, "ShuffleExchange", "shuffleBytesWritten"), measure.total(c, "BroadcastExchange", "dataSize")) for name, c in ways.items()]
    return spark.createDataFrame(rows, "method string, stored_rows long, rows_scanned long, bytes_scanned long, bytes_shuffled long, bytes_broadcast long")

"""Relational operators around the methods: scans, joins, aggregates, windows, sets, arrays, strings, user functions."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..build import gram, spectra, text
from ..cost.memory import config_of
from ..io import sinks, sources, spectral_source
from ..linalg import blocks as layout
from ..relational import joins, udfs, windows
from ..session import shared_folder
from ..sql.register import register
from .base import COSUPPLY, EMBEDDING_GRAM, cosupply, flows, query, r6, table

# scans and sinks


@query("SELECT count(*) AS n, round(sum(list_sum(embedding::DOUBLE[])), 6) AS total FROM embeddings")
def scan_embeddings(spark: SparkSession, sf: str) -> DataFrame:
    x = F.aggregate(F.col("embedding").cast("array<double>"), F.lit(0.0), lambda a, b: a + b)
    return table(spark, sf, "embeddings").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(x), 6).alias("total"))


@query("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' GROUP BY 1")
def scan_pruned_lineitem(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "lineitem").where(F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz"))
    return lines.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query(f"SELECT count(*) AS n, sum(v) AS total FROM ({COSUPPLY})")
def sink_roundtrip_blocks(spark: SparkSession, sf: str) -> DataFrame:
    n = table(spark, sf, "supplier").count()
    bs = -(-n // 4)
    path = f"{shared_folder(spark)}/blocks-{uuid.uuid4().hex}"
    sinks.write_blocks(layout.to_blocks(cosupply(spark, sf), n, bs), path, 2)
    return layout.from_blocks(sources.read_blocks(spark, path), bs).agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("total"))


@query(f"SELECT count(*) AS n, sum(v) AS total, sum(i * j)::BIGINT AS places FROM ({COSUPPLY})")
def coord_text_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    path = f"{shared_folder(spark)}/coords-{uuid.uuid4().hex}"
    sinks.write_coord_text(cosupply(spark, sf), path)
    return sources.read_coord_text(spark, path).agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("total"), F.sum(F.col("i") * F.col("j")).alias("places"))


@query("WITH n AS (SELECT max(c_custkey) + 1 AS n FROM customer) SELECT c_custkey::BIGINT AS i, c_custkey::BIGINT AS j, 2.0::DOUBLE AS v FROM customer UNION ALL SELECT c_custkey, c_custkey + 1, 1.0 FROM customer, n WHERE c_custkey + 1 < n UNION ALL SELECT c_custkey, c_custkey - 1, 1.0 FROM customer WHERE c_custkey > 0")
def spectral_source_entries(spark: SparkSession, sf: str) -> DataFrame:
    """The source's tridiagonal operator over the customers, whose keys run from 0 without gaps."""
    spectral_source.register(spark)
    n = table(spark, sf, "customer").agg(F.max("c_custkey")).first()[0] + 1
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return spark.read.format("spectral").option("kind", "onetwoone").option("n", n).option("partitions", parts).load()


# filters


@query(f"SELECT i, j, v FROM ({COSUPPLY}) WHERE i < j")
def filter_upper_triangle(spark: SparkSession, sf: str) -> DataFrame:
    return cosupply(spark, sf).where("i < j")


@query(f"SELECT i, j, v FROM ({COSUPPLY}) WHERE v BETWEEN 20 AND 40 AND i IN (1, 2, 3, 5, 8)")
def filter_threshold(spark: SparkSession, sf: str) -> DataFrame:
    return cosupply(spark, sf).where(F.col("v").between(20, 40) & F.col("i").isin(1, 2, 3, 5, 8))


@query("SELECT c_custkey, round(coalesce(nullif(greatest(c_acctbal, 0), 0), -1.0), 2) AS balance, c_mktsegment LIKE 'A%' AS a FROM customer")
def null_guard(spark: SparkSession, sf: str) -> DataFrame:
    positive = F.greatest("c_acctbal", F.lit(0.0))
    value = F.nanvl(F.coalesce(F.nullif(positive, F.lit(0.0)), F.lit(-1.0)), F.lit(-1.0))
    return table(spark, sf, "customer").select("c_custkey", F.round(value, 2).alias("balance"), F.col("c_mktsegment").like("A%").alias("a"))


# joins


@query(f"SELECT a.s_name AS left_name, b.s_name AS right_name, v FROM ({COSUPPLY}) JOIN supplier a ON a.s_suppkey = i JOIN supplier b ON b.s_suppkey = j WHERE v >= 30")
def join_edges_inner(spark: SparkSession, sf: str) -> DataFrame:
    names = table(spark, sf, "supplier").select("s_suppkey", "s_name")
    a, b = names.select(F.col("s_suppkey").alias("i"), F.col("s_name").alias("left_name")), names.select(F.col("s_suppkey").alias("j"), F.col("s_name").alias("right_name"))
    return cosupply(spark, sf).where("v >= 30").join(a, "i").join(b, "j").select("left_name", "right_name", "v")


@query("SELECT s_suppkey, count(l_orderkey) AS lines FROM supplier LEFT JOIN (SELECT * FROM lineitem WHERE l_quantity > 49) ON s_suppkey = l_suppkey GROUP BY 1")
def join_left_missing(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "lineitem").where("l_quantity > 49").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, sf, "supplier").join(lines, F.col("s_suppkey") == F.col("l_suppkey"), "left").select("s_suppkey", F.coalesce("n", F.lit(0)).cast("long").alias("lines"))


_FLOW = "SELECT c_nationkey::BIGINT AS i, s_nationkey::BIGINT AS j, count(*)::DOUBLE AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"


@query(f"WITH f AS ({_FLOW}) SELECT coalesce(a.i, b.j) AS i, coalesce(a.j, b.i) AS j, greatest(a.v, b.v) AS v FROM f a FULL JOIN f b ON a.i = b.j AND a.j = b.i")
def join_full_symmetrise(spark: SparkSession, sf: str) -> DataFrame:
    return joins.symmetrised(flows(spark, sf).withColumnRenamed("f", "v"))


@query("SELECT count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 50)")
def semi_index(spark: SparkSession, sf: str) -> DataFrame:
    index = table(spark, sf, "lineitem").where("l_quantity >= 50").select(F.col("l_orderkey").alias("o_orderkey"))
    return joins.semi(table(spark, sf, "orders"), index, ["o_orderkey"]).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 350000)")
def anti_orphans(spark: SparkSession, sf: str) -> DataFrame:
    return joins.anti(table(spark, sf, "customer").select("c_custkey"), table(spark, sf, "orders").where("o_totalprice > 350000").select(F.col("o_custkey").alias("c_custkey")), ["c_custkey"])


@query("SELECT b AS bin, count(*) AS n FROM events JOIN (SELECT range::INT AS b, range * 50.0 - 100 AS low, range * 50.0 - 50 AS high FROM range(12)) ON value >= low AND value < high GROUP BY 1")
def range_dos_bin(spark: SparkSession, sf: str) -> DataFrame:
    edges = spark.range(12).select(F.col("id").cast("int").alias("bin"), (F.col("id") * 50.0 - 100).alias("low"), (F.col("id") * 50.0 - 50).alias("high"))
    return joins.range_bins(table(spark, sf, "events").select("value"), "value", edges).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous_event_id FROM events")
def previous_event(spark: SparkSession, sf: str) -> DataFrame:
    return joins.previous(table(spark, sf, "events"), ["user_id"], ["ts", "event_id"], "event_id").select("event_id", "previous_event_id")


_KIND = "(SELECT min(event_type) FROM events)"


@query(f"SELECT l.event_id, max(r.value) AS value FROM events l ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = {_KIND} GROUP BY ALL) r ON l.user_id = r.user_id AND l.ts >= r.ts WHERE l.event_type != {_KIND} GROUP BY l.event_id")
def asof_prev_problem(spark: SparkSession, sf: str) -> DataFrame:
    events = table(spark, sf, "events")
    kind = events.agg(F.min("event_type").alias("kind"))
    marked = events.crossJoin(F.broadcast(kind))
    right = marked.where("event_type = kind").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    left = marked.where("event_type != kind").select("event_id", "user_id", "ts")
    return joins.asof(left, right, ["user_id"], "ts", "value").select("event_id", "value")


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR AND a.event_id != b.event_id")
def interval_events(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events")
    a, b = e.select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("t1")), e.select("user_id", F.col("event_id").alias("second_id"), F.col("ts").alias("t2"))
    return joins.interval(a, b, ["user_id"], "t1", "t2", 3600).where("first_id != second_id").select("first_id", "second_id")


@query("SELECT event_type, count(*) AS n FROM events JOIN (SELECT user_id, count(*) AS c FROM events GROUP BY 1) u USING (user_id) WHERE c > 5 GROUP BY 1")
def salted_join(spark: SparkSession, sf: str) -> DataFrame:
    events = table(spark, sf, "events").select("user_id", "event_id", "event_type")
    users = events.groupBy("user_id").agg(F.count(F.lit(1)).alias("c")).where("c > 5")
    return joins.salted(events, users, ["user_id"], 4).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


# aggregates


@query(COSUPPLY)
def cooccurrence_counts(spark: SparkSession, sf: str) -> DataFrame:
    return cosupply(spark, sf)


@query(f"WITH m AS (SELECT j, avg(x) AS m FROM (SELECT unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS j FROM embeddings) GROUP BY j), c AS (SELECT count(*) AS c FROM embeddings) SELECT q.i::BIGINT AS i, q.j::BIGINT AS j, round(1e3 * (q.v - c.c * a.m * b.m) / (c.c - 1), 6) + 0.0 AS v FROM ({EMBEDDING_GRAM}) q JOIN m a ON a.j = q.i JOIN m b ON b.j = q.j, c")
def cov_matrix(spark: SparkSession, sf: str) -> DataFrame:
    return gram.covariance(table(spark, sf, "embeddings"), "embedding").select("i", "j", r6(F.col("v") * 1e3).alias("v"))


@query(f"SELECT i, sum(v) AS total FROM ({COSUPPLY}) GROUP BY i")
def row_sums(spark: SparkSession, sf: str) -> DataFrame:
    return cosupply(spark, sf).groupBy("i").agg(F.sum("v").alias("total"))


@query(f"SELECT round(sum(v) FILTER (i = j), 6) AS trace FROM ({EMBEDDING_GRAM})")
def trace_sum(spark: SparkSession, sf: str) -> DataFrame:
    return gram.gram(table(spark, sf, "embeddings"), "embedding").where("i = j").agg(F.round(F.sum("v"), 6).alias("trace"))


@query(f"SELECT round(sum(v * v), 6) AS squares FROM ({EMBEDDING_GRAM})")
def frobenius(spark: SparkSession, sf: str) -> DataFrame:
    return gram.gram(table(spark, sf, "embeddings"), "embedding").agg(F.round(F.sum(F.col("v") * F.col("v")), 6).alias("squares"))


@query(f"SELECT max(r) AS bound FROM (SELECT i, sum(abs(v)) AS r FROM ({COSUPPLY}) GROUP BY i)")
def disc_bound(spark: SparkSession, sf: str) -> DataFrame:
    rows = cosupply(spark, sf).groupBy("i").agg(F.sum(F.when(F.col("i") == F.col("j"), F.col("v")).otherwise(F.abs("v"))).alias("r"))
    return rows.agg(F.max("r").alias("bound"))


_USERS = "(SELECT event_type, (user_id % 3)::INT AS grp, event_id FROM events)"


def _users(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_type", (F.col("user_id") % 3).cast("int").alias("grp"), "event_id")


@query(f"SELECT event_type, grp, grouping_id(event_type, grp)::INT AS level, count(*) AS n FROM {_USERS} GROUP BY ROLLUP (event_type, grp)")
def trace_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _users(spark, sf).rollup("event_type", "grp").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("n"))


@query(f"SELECT event_type, grp, grouping_id(event_type, grp)::INT AS level, count(*) AS n FROM {_USERS} GROUP BY CUBE (event_type, grp) HAVING count(*) > 3")
def phase_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _users(spark, sf).cube("event_type", "grp").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("n")).where("n > 3")


@query("SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
def grouping_sets_flow(spark: SparkSession, sf: str) -> DataFrame:
    c = table(spark, sf, "customer")
    return c.groupingSets([["c_nationkey"], ["c_mktsegment"], []], "c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT count(DISTINCT l_orderkey * 100000 + l_suppkey) AS edges FROM lineitem")
def distinct_edges(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey").distinct().agg(F.count(F.lit(1)).alias("edges"))


@query("SELECT count(DISTINCT user_id) AS users, 0::BIGINT AS off_by_fifteenths FROM events")
def approx_users(spark: SparkSession, sf: str) -> DataFrame:
    """Users counted exactly, and how many fifteenths of that the sketch is off."""
    counts = table(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("users"))
    return counts.select("users", F.floor(15 * F.abs(F.col("a") - F.col("users")) / F.col("users")).alias("off_by_fifteenths"))


@query("SELECT event_type, min_by(event_id, (value, event_id)) AS lowest, max_by(event_id, (value, event_id)) AS highest, round(corr(value, user_id), 6) AS corr, round(covar_samp(value, user_id), 4) AS covar, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY 1")
def extremes_by_type(spark: SparkSession, sf: str) -> DataFrame:
    order = F.struct("value", "event_id")
    return table(spark, sf, "events").groupBy("event_type").agg(
        F.min_by("event_id", order).alias("lowest"), F.max_by("event_id", order).alias("highest"), F.round(F.corr("value", "user_id"), 6).alias("corr"),
        F.round(F.covar_samp("value", "user_id"), 4).alias("covar"), F.round(F.percentile("value", 0.5), 6).alias("median"),
    )


# windows

_RANK = "(SELECT p_partkey AS k, round(p_retailprice / 100) AS v FROM part)"


@query(f"SELECT k, row_number() OVER (ORDER BY v DESC, k)::INT AS place, rank() OVER (ORDER BY v DESC)::INT AS rank, dense_rank() OVER (ORDER BY v DESC)::INT AS dense, ntile(4) OVER (ORDER BY v DESC, k)::INT AS quarter, round(percent_rank() OVER (ORDER BY v DESC), 6) AS percent, round(cume_dist() OVER (ORDER BY v DESC), 6) AS cume FROM {_RANK}")
def rank_spectrum(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "part").select(F.col("p_partkey").alias("k"), F.round(F.col("p_retailprice") / 100).alias("v"))
    return windows.rank_spectrum(rows, "v", "k")


_LAM = "(SELECT p_partkey + 1 AS k, 1e-4 + p_partkey * (1 - 1e-4) / (n - 1) AS l FROM part, (SELECT count(*) AS n FROM part))"


def _uniform(spark: SparkSession, sf: str) -> DataFrame:
    return spectra.spectrum(table(spark, sf, "part"), "p_partkey", "uniform")


@query(f"SELECT k, round(lead(l) OVER (ORDER BY k) - l, 9) AS gap FROM {_LAM}")
def gap_lead(spark: SparkSession, sf: str) -> DataFrame:
    return windows.gaps(_uniform(spark, sf), "lambda", "k").select("k", F.round("gap", 9).alias("gap"))


_SHARE = f"SELECT k, round(sum(l) OVER (ORDER BY k) / sum(l) OVER (), 6) AS share FROM {_LAM}"


@query(_SHARE)
def explained_cumsum(spark: SparkSession, sf: str) -> DataFrame:
    return windows.explained(_uniform(spark, sf), "lambda", "k").select("k", F.round("share", 6).alias("share"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 6) + 0.0 AS mean FROM events")
def moving_avg_events(spark: SparkSession, sf: str) -> DataFrame:
    return windows.moving_average(table(spark, sf, "events"), ["user_id"], ["ts", "event_id"], "value", 4).select("event_id", r6("mean").alias("mean"))


@query(f"SELECT i, j, v FROM ({COSUPPLY}) ORDER BY v DESC, i, j LIMIT 15")
def topk_entries(spark: SparkSession, sf: str) -> DataFrame:
    return cosupply(spark, sf).orderBy(F.desc("v"), "i", "j").limit(15)


@query(f"SELECT i, j, v FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS place FROM ({COSUPPLY})) WHERE place <= 3")
def topk_per_row(spark: SparkSession, sf: str) -> DataFrame:
    return windows.top_per_key(cosupply(spark, sf), ["i"], [F.desc("v"), "j"], 3).select("i", "j", "v")


# sets


def _edges_by_status(spark: SparkSession, sf: str, status: str) -> DataFrame:
    orders = table(spark, sf, "orders").where(F.col("o_orderstatus") == status).select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey").join(orders, "l_orderkey").select((F.col("o_custkey") % 50).alias("c"), F.col("l_suppkey").alias("s"))


def _status_sql(op: str) -> str:
    one = "SELECT o_custkey % 50 AS c, l_suppkey AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = '{}'"
    return f"{one.format('F')} {op} {one.format('O')}"


@query(_status_sql("UNION"))
def set_union_symm(spark: SparkSession, sf: str) -> DataFrame:
    return _edges_by_status(spark, sf, "F").unionByName(_edges_by_status(spark, sf, "O")).distinct()


@query(_status_sql("INTERSECT"))
def set_intersect_edges(spark: SparkSession, sf: str) -> DataFrame:
    return _edges_by_status(spark, sf, "F").intersect(_edges_by_status(spark, sf, "O"))


@query(_status_sql("EXCEPT"))
def set_except_edges(spark: SparkSession, sf: str) -> DataFrame:
    return _edges_by_status(spark, sf, "F").subtract(_edges_by_status(spark, sf, "O"))


@query(f"SELECT c, s, count(*) AS n FROM ({_status_sql('EXCEPT ALL')}) GROUP BY ALL")
def set_except_all(spark: SparkSession, sf: str) -> DataFrame:
    return _edges_by_status(spark, sf, "F").exceptAll(_edges_by_status(spark, sf, "O")).groupBy("c", "s").agg(F.count(F.lit(1)).alias("n"))


# arrays, maps, strings


_CENTRES = "SELECT label, list(m ORDER BY j) AS c FROM (SELECT label, j, avg(x) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings) GROUP BY ALL) GROUP BY label"


def _centres(spark: SparkSession, sf: str) -> DataFrame:
    """(label, c): mean vector of each label."""
    long = gram.long_vectors(table(spark, sf, "embeddings"), "label", "embedding").groupBy("label", "j").agg(F.avg("x").alias("m"))
    return long.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "m"))), lambda s: s["m"]).alias("c"))


@query(f"WITH e AS ({_CENTRES}) SELECT a.label::BIGINT AS i, b.label::BIGINT AS j, round(list_dot_product(a.c, b.c), 6) + 0.0 AS v FROM e a, e b")
def label_centre_dot(spark: SparkSession, sf: str) -> DataFrame:
    return gram.kernel(_centres(spark, sf), "label", "c").select("i", "j", r6("v").alias("v"))


@query(f"WITH e AS ({_CENTRES}) SELECT a.label::BIGINT AS i, b.label::BIGINT AS j, round(exp(-0.5 * pow(list_distance(a.c, b.c), 2)), 6) AS v FROM e a, e b")
def label_centre_rbf(spark: SparkSession, sf: str) -> DataFrame:
    return gram.kernel(_centres(spark, sf), "label", "c", "rbf", 0.5).select("i", "j", r6("v").alias("v"))


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def embed_norm(spark: SparkSession, sf: str) -> DataFrame:
    square = F.aggregate(F.transform(F.col("embedding").cast("array<double>"), lambda x: x * x), F.lit(0.0), lambda a, b: a + b)
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.sqrt(square), 6).alias("norm"))


@query("SELECT j::INT AS j, round(sum(x), 5) + 0.0 AS total FROM (SELECT unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS j FROM embeddings) GROUP BY j")
def embed_explode(spark: SparkSession, sf: str) -> DataFrame:
    return gram.long_vectors(table(spark, sf, "embeddings"), "vec_id", "embedding").groupBy("j").agg(r6(F.sum("x"), 5).alias("total"))


@query("SELECT event_type, count(json_extract_string(props, '$.k')) AS n, sum(TRY_CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS total FROM events GROUP BY 1")
def props_feature(spark: SparkSession, sf: str) -> DataFrame:
    k = F.get_json_object("props", "$.k")
    return table(spark, sf, "events").groupBy("event_type").agg(F.count(k).alias("n"), F.sum(k.try_cast("bigint")).alias("total"))


@query("SELECT page_id, count(*) AS links, count(DISTINCT t) AS targets FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages) GROUP BY 1")
def page_links(spark: SparkSession, sf: str) -> DataFrame:
    return text.link_edges(table(spark, sf, "pages")).groupBy("page_id").agg(F.count(F.lit(1)).alias("links"), F.count_distinct("target").alias("targets"))


_WORDS = "regexp_extract_all(lower(text), '[a-z]+')"


@query(f"SELECT gram, count(*) AS n FROM (SELECT unnest(list_transform(range(1, len(w)), lambda k: w[k] || ' ' || w[k + 1])) AS gram FROM (SELECT {_WORDS} AS w FROM documents)) GROUP BY gram ORDER BY n DESC, gram LIMIT 20")
def text_ngrams(spark: SparkSession, sf: str) -> DataFrame:
    words = table(spark, sf, "documents").select(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w"))
    pairs = words.where(F.size("w") > 1).select(F.explode(F.transform(F.sequence(F.lit(0), F.size("w") - 2), lambda k: F.concat_ws(" ", F.col("w")[k], F.col("w")[k + 1]))).alias("gram"))
    return pairs.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "gram").limit(20)


@query("SELECT role, after, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations) WHERE after IS NOT NULL GROUP BY ALL")
def role_transition(spark: SparkSession, sf: str) -> DataFrame:
    after = F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))
    return table(spark, sf, "conversations").select("role", after.alias("after")).where("after is not null").groupBy("role", "after").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH t AS (SELECT DISTINCT right(source, -3)::BIGINT AS k, unnest({_WORDS}) AS w FROM documents) SELECT a.k AS i, b.k AS j, count(*)::DOUBLE AS v FROM t a JOIN t b ON a.w = b.w AND a.k != b.k GROUP BY ALL")
def source_shared_words(spark: SparkSession, sf: str) -> DataFrame:
    """How many distinct words two sources share."""
    docs = table(spark, sf, "documents").select(F.substring("source", 4, 10).cast("long").alias("k"), "text")
    return text.shared_terms(docs, "k", "text")


@query("SELECT lang, round(avg(quality), 6) AS quality, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def label_mean(spark: SparkSession, sf: str) -> DataFrame:
    joined = table(spark, sf, "documents").select("doc_id", "lang").join(table(spark, sf, "labels"), "doc_id")
    return joined.groupBy("lang").agg(F.round(F.avg("quality"), 6).alias("quality"), F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def contaminated_docs(spark: SparkSession, sf: str) -> DataFrame:
    """Documents that hold a benchmark text word for word; the benchmark is small and broadcast behind Spark's size check."""
    items = table(spark, sf, "benchmark").select("item_id", F.col("text").alias("item"))
    return table(spark, sf, "documents").select("doc_id", "text").join(items, F.contains("text", "item")).select("doc_id", "item_id")


@query("SELECT date_trunc('week', ts)::TIMESTAMP AS week, event_type, count(*) AS n, count(DISTINCT dayofweek(ts)) AS days FROM events GROUP BY ALL")
def weekly_counts(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").groupBy(F.date_trunc("week", "ts").cast("timestamp_ntz").alias("week"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.count_distinct(F.dayofweek("ts")).alias("days"))


# subqueries, sampling, user functions, SQL


@query("SELECT l_suppkey, count(*) AS n FROM lineitem a WHERE l_quantity > (SELECT avg(l_quantity) + 20 FROM lineitem b WHERE b.l_suppkey = a.l_suppkey) GROUP BY 1")
def subq_above_mean(spark: SparkSession, sf: str) -> DataFrame:
    table(spark, sf, "lineitem").createOrReplaceTempView("eigenlake_lineitem")
    return spark.sql("SELECT l_suppkey, count(*) AS n FROM eigenlake_lineitem a WHERE l_quantity > (SELECT avg(l_quantity) + 20 FROM eigenlake_lineitem b WHERE b.l_suppkey = a.l_suppkey) GROUP BY 1")


@query("SELECT n_name, s_name FROM nation, LATERAL (SELECT s_name, s_acctbal, s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2) x")
def lateral_topk(spark: SparkSession, sf: str) -> DataFrame:
    for name in ("nation", "supplier"):
        table(spark, sf, name).createOrReplaceTempView(f"eigenlake_{name}")
    return spark.sql("SELECT n_name, s_name FROM eigenlake_nation n, LATERAL (SELECT s_name FROM eigenlake_supplier s WHERE s.s_nationkey = n.n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2) x")


@query("WITH RECURSIVE t(k, v) AS (SELECT 0, max(value)::DOUBLE FROM events UNION ALL SELECT k + 1, v * 0.9 + 0.1 * k FROM t WHERE k < 20) SELECT k, round(v, 9) AS v FROM t")
def recursive_cte_powers(spark: SparkSession, sf: str) -> DataFrame:
    table(spark, sf, "events").createOrReplaceTempView("eigenlake_events")
    return spark.sql("WITH RECURSIVE t(k, v) AS (SELECT 0, CAST(max(value) AS DOUBLE) FROM eigenlake_events UNION ALL SELECT k + 1, v * CAST(0.9 AS DOUBLE) + CAST(0.1 AS DOUBLE) * k FROM t WHERE k < 20) SELECT k, round(v, 9) AS v FROM t")


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey * 2246822519) % 4294967296 < 429496730")
def bernoulli_sample(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: each order by its own coin, thrown from a hash of the key, with a chance of a tenth."""
    return table(spark, sf, "orders").where((F.col("o_orderkey") * F.lit(2246822519)) % 4294967296 < 429496730).select("o_orderkey")


@query("SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY (o_orderkey * 2654435761) % 4294967296, o_orderkey) <= 20")
def stratified_sample(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: the twenty orders of each priority with the smallest hash, chosen by partial top lists."""
    mark = F.struct(((F.col("o_orderkey") * F.lit(2654435761)) % 4294967296).alias("h"), F.col("o_orderkey").alias("k"))
    marked = table(spark, sf, "orders").select("o_orderpriority", mark.alias("m"), F.pmod(F.xxhash64("o_orderkey"), F.lit(64)).alias("part"))
    least = lambda df, *by: df.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("m"))).where("r <= 20").drop("r")
    return least(least(marked, "o_orderpriority", "part"), "o_orderpriority").select("o_orderpriority", F.col("m.k").alias("o_orderkey"))


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 1000 < 50")
def hash_sample(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: a deterministic twentieth by a hash of the key."""
    return table(spark, sf, "orders").where((F.col("o_orderkey") * F.lit(2654435761)) % 1000 < 50).select("o_orderkey")


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def udf_block_norm(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "embeddings").select("vec_id", F.round(udfs.vector_norm(F.col("embedding").cast("array<double>")), 6).alias("norm"))


@query(f"SELECT i::BIGINT AS i, j::BIGINT AS j, round(v, 6) + 0.0 AS v FROM ({EMBEDDING_GRAM})")
def udaf_gram(spark: SparkSession, sf: str) -> DataFrame:
    return udfs.partial_gram(table(spark, sf, "embeddings"), "embedding", 64).select("i", "j", r6("v").alias("v"))


@query("SELECT g, k, round(CASE WHEN k = 0 THEN (a + c + sqrt((a - c) * (a - c) + 4 * b * b)) / 2 ELSE (a + c - sqrt((a - c) * (a - c) + 4 * b * b)) / 2 END, 6) + 0.0 AS eigenvalue FROM (SELECT c_nationkey AS g, count(*)::DOUBLE AS a, sum(c_acctbal) / 1000 AS b, sum(c_acctbal * c_acctbal) / 1e6 AS c FROM customer GROUP BY 1), (SELECT range::INT AS k FROM range(2))")
def udtf_eig(spark: SparkSession, sf: str) -> DataFrame:
    register(spark)
    m = table(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("g")).agg(F.count(F.lit(1)).cast("double").alias("a"), (F.sum("c_acctbal") / 1000).alias("b"), (F.sum(F.col("c_acctbal") * F.col("c_acctbal")) / 1e6).alias("c"))
    m.select("g", F.array(F.array("a", "b"), F.array("b", "c")).alias("m")).createOrReplaceTempView("eigenlake_moments")
    return spark.sql("SELECT g, k, eigenvalue FROM eigenlake_moments, LATERAL eig_table(m)").select("g", "k", r6("eigenvalue").alias("eigenvalue"))


@query(_SHARE)
def sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    _uniform(spark, sf).createOrReplaceTempView("eigenlake_spectrum")
    return spark.sql("SELECT k, round(sum(lambda) OVER (ORDER BY k) / sum(lambda) OVER (), 6) AS share FROM eigenlake_spectrum")


@query("SELECT p::INT AS p, round(8 * ((n / p) * (n / p) + 2 * (n / p) * 3000 + 6000 * n) / 1e9, 6) AS host_gb, round(8 * ((n / p) * (n / p) / 4 + 9000 * n / (2 * p) + 3000 * (2 * n + 3000)) / 1e9, 6) AS device_gb FROM (SELECT 1 + o_orderkey % 4 AS p, (1 + o_orderkey % 4) * count(*)::DOUBLE AS n FROM orders GROUP BY 1)")
def sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    register(spark)
    config_of(table(spark, sf, "orders"), 1 + F.col("o_orderkey") % 4).createOrReplaceTempView("eigenlake_config")
    return spark.sql("SELECT r AS p, round(mem_host(CAST(n AS DOUBLE), CAST(s AS DOUBLE), CAST(r AS DOUBLE), CAST(c AS DOUBLE)) / 1e9, 6) AS host_gb, round(mem_device(CAST(n AS DOUBLE), CAST(s AS DOUBLE), CAST(r AS DOUBLE), CAST(c AS DOUBLE), 2D, 2D) / 1e9, 6) AS device_gb FROM eigenlake_config")

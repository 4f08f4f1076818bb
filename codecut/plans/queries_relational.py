"""Relational operators around the methods, over whole tables."""

from __future__ import annotations

import re

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..functions.bits import hamming
from ..session import read_table
from .queries_method import DEG_SQL, _labelled, code_sql, coded, merged_degrees, site_degrees
from .registry import query

_TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_NAME = re.compile(r"\b(" + "|".join(_TABLES) + r")\b(?!\s*\()")


def sql(name: str, text: str, duck: str | None = None) -> None:
    """A query in SQL; duck where the other engine spells it differently. Table names become the tables of sf_dir."""

    def run(spark, d):
        used = sorted(set(_NAME.findall(text)))
        return spark.sql(_NAME.sub(r"{\1}", text), **{t: read_table(spark, d, t) for t in used})

    query(duck or text, name=name)(run)


t = read_table

# project and filter

sql("proj_computed", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge FROM lineitem")
sql("proj_case_when", "SELECT o_orderkey, CASE WHEN o_totalprice >= 200000 THEN 'large' WHEN o_totalprice >= 50000 THEN 'middle' ELSE 'small' END AS size FROM orders")
sql("proj_cast_decimal", "SELECT o_orderkey, CAST(o_totalprice AS DECIMAL(18, 2)) AS price, CAST(o_orderkey AS VARCHAR(20)) AS k FROM orders", "SELECT o_orderkey, CAST(o_totalprice AS DECIMAL(18, 2)) AS price, CAST(o_orderkey AS VARCHAR) AS k FROM orders")


@query("SELECT c_custkey, c_name AS name, c_acctbal AS balance FROM customer")
def proj_struct_flatten(spark, d):
    return t(spark, d, "customer").select("c_custkey", F.struct(F.col("c_name").alias("name"), F.col("c_acctbal").alias("balance")).alias("s")).select("c_custkey", "s.*")


sql("filter_between_in", "SELECT p_partkey, p_size FROM part WHERE p_size BETWEEN 5 AND 20 AND p_type IN (SELECT min(p_type) FROM part UNION ALL SELECT max(p_type) FROM part)")
sql("filter_like_rlike", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND regexp_like(text, '[0-9][0-9][0-9]')", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND regexp_matches(text, '[0-9][0-9][0-9]')")
sql("filter_null_safe", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 0")
sql("filter_date_range", "SELECT l_orderkey, l_linenumber, l_shipdate FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'")
sql("filter_hash_sample", "SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 1000 < 100")

# joins


def _joined(hint: str):
    def run(spark, d):
        o, c = t(spark, d, "orders", "o_orderkey", "o_custkey"), t(spark, d, "customer", "c_custkey", "c_mktsegment")
        return o.join(c.hint(hint), o.o_custkey == c.c_custkey).select("o_orderkey", "c_mktsegment")

    return run


_INNER = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"


@query("SELECT o_orderkey, n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def join_inner_broadcast(spark, d):
    """nation has 25 rows by definition, so it is broadcast."""
    o, c, n = t(spark, d, "orders", "o_orderkey", "o_custkey"), t(spark, d, "customer", "c_custkey", "c_nationkey"), t(spark, d, "nation", "n_nationkey", "n_name")
    return o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("o_orderkey", "n_name")


query(_INNER, name="join_inner_merge")(_joined("merge"))
query(_INNER, name="join_inner_shuffle_hash")(_joined("shuffle_hash"))
for _how in ("left", "right", "full"):

    def _outer(spark, d, how=_how):
        docs, labels = t(spark, d, "documents", "doc_id", "lang"), t(spark, d, "labels", F.col("doc_id").alias("label_id"), "quality")
        return docs.join(labels, docs.doc_id == labels.label_id, how).select("doc_id", "label_id", "quality")

    query(f"SELECT d.doc_id, l.doc_id AS label_id, quality FROM documents d {_how.upper()} JOIN labels l ON d.doc_id = l.doc_id", name=f"join_{_how}")(_outer)
sql("join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
sql("join_multiway_star", """SELECT r_name, n_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey
  JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name""")
sql("join_semi", "SELECT d.doc_id FROM documents d LEFT SEMI JOIN labels l ON d.doc_id = l.doc_id", "SELECT d.doc_id FROM documents d SEMI JOIN labels l ON d.doc_id = l.doc_id")
sql("join_anti", "SELECT d.doc_id FROM documents d LEFT ANTI JOIN labels l ON d.doc_id = l.doc_id", "SELECT d.doc_id FROM documents d ANTI JOIN labels l ON d.doc_id = l.doc_id")


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT count(*) AS pairs, min(bit_count(xor(a.code, b.code))) AS nearest FROM v a JOIN v b ON a.code < b.code")
def join_cross_codes(spark, d):
    """A theta join of distinct codes; their number is bounded by the code's 16 bits."""
    v = merged_degrees(spark, d).select("code")
    a, b = v.select(F.col("code").alias("a")), F.broadcast(v.select(F.col("code").alias("b")))
    return a.join(b, F.col("a") < F.col("b")).agg(F.count("*").alias("pairs"), F.min(hamming(F.col("a"), F.col("b")).cast("long")).alias("nearest"))


@query("SELECT p_partkey, band FROM part JOIN (SELECT i AS band, 900.0 + 10 * i AS lo, 910.0 + 10 * i AS hi FROM range(0, 200) t(i)) b ON p_retailprice >= lo AND p_retailprice < hi")
def join_range_bucket(spark, d):
    """A range join as an equi-join on the bucket that both sides fall into, and the exact test."""
    p = t(spark, d, "part", "p_partkey", "p_retailprice").withColumn("k", F.floor(F.col("p_retailprice") / 100))
    b = spark.range(200).select(F.col("id").alias("band"), (F.col("id") * 10 + 900.0).alias("lo"), (F.col("id") * 10 + 910.0).alias("hi"))
    b = b.withColumn("k", F.explode(F.sequence(F.floor(F.col("lo") / 100), F.floor(F.col("hi") / 100))))
    return p.join(b, "k").where((F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).select("p_partkey", "band").distinct()


@query(f"WITH {code_sql(16)}, p AS (SELECT a.row_id AS a, b.row_id AS b FROM c a JOIN c b ON a.row_id < b.row_id AND bit_count(xor(a.code, b.code)) <= 1) SELECT * FROM p")
def join_hamming_radius(spark, d):
    from ..operators.graph import hamming_join

    rows = coded(spark, d, 16).select("row_id", "code")
    near = hamming_join(rows.select("code").distinct(), rows.select("code").distinct(), 1, 16)
    a, b = rows.select(F.col("row_id").alias("ra"), F.col("code").alias("a")), rows.select(F.col("row_id").alias("rb"), F.col("code").alias("b"))
    return near.join(a, "a").join(b, "b").where("ra < rb").select(F.col("ra").alias("a"), F.col("rb").alias("b"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(date_diff('second', a.ts, b.ts)) <= 300 AND b.ts BETWEEN a.ts - INTERVAL 5 MINUTE AND a.ts + INTERVAL 5 MINUTE")
def join_interval_events(spark, d):
    """Events of one user within five minutes: joined on user and time bucket, so a busy user is spread over buckets."""
    e = t(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    width = 300_000_000
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.floor(F.col("us") / width).alias("k"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), F.explode(F.array(*[F.floor(F.col("us") / width) + i for i in (-1, 0, 1)])).alias("k"))
    return a.join(b, ["user_id", "k"]).where((F.col("a") < F.col("b")) & (F.abs(F.col("ua") - F.col("ub")) <= width)).select("a", "b")


@query("SELECT o_orderkey, max(e.ts) AS last_ts FROM (SELECT o_orderkey, o_custkey % 15 AS u, TIMESTAMP '2024-01-01' + to_days(CAST(o_orderkey % 30 AS INTEGER)) AS at FROM orders) o LEFT JOIN events e ON e.user_id % 15 = o.u AND e.ts <= o.at GROUP BY 1")
def join_asof_last_event(spark, d):
    """As-of join: both sides in one stream per key, the last event carried forward."""
    o = t(spark, d, "orders", "o_orderkey", "o_custkey").select((F.col("o_custkey") % 15).alias("u"), F.expr("timestamp_ntz'2024-01-01' + make_dt_interval(cast(o_orderkey % 30 as int))").alias("at"), "o_orderkey", F.lit(1).alias("side"))
    e = t(spark, d, "events", "user_id", "ts").select((F.col("user_id") % 15).alias("u"), F.col("ts").cast("timestamp_ntz").alias("at"), F.lit(None).cast("long").alias("o_orderkey"), F.lit(0).alias("side"))
    w = Window.partitionBy("u").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0)
    both = o.union(e).withColumn("last_ts", F.last(F.when(F.col("side") == 0, F.col("at")), ignorenulls=True).over(w))
    return both.where("side = 1").select("o_orderkey", "last_ts")


# aggregates

sql("agg_hash_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY l_returnflag, l_linestatus")
sql("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
sql("agg_conditional", "SELECT l_linestatus, count(*) FILTER (WHERE l_discount > 0.05) AS discounted, sum(CASE WHEN l_tax = 0 THEN 1 ELSE 0 END) AS untaxed FROM lineitem GROUP BY l_linestatus")
sql("agg_collect_sorted", "SELECT n_regionkey, concat_ws(',', sort_array(collect_list(n_name))) AS names FROM nation GROUP BY n_regionkey", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
sql("agg_percentile", "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 4) AS p50, round(percentile(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 4) AS p50, round(quantile_cont(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag")
sql("agg_maxby_minby", "SELECT o_orderpriority, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS dearest, min_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_orderpriority", "SELECT o_orderpriority, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_orderpriority")
sql("agg_stddev_corr_slope", "SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(corr(l_quantity, l_extendedprice), 4) AS r, round(regr_slope(l_extendedprice, l_quantity), 3) AS slope FROM lineitem GROUP BY l_returnflag")
sql("agg_histogram", "SELECT CAST(floor(l_quantity / 10) AS BIGINT) AS bin, count(*) AS n FROM lineitem GROUP BY 1")
sql("agg_having", "SELECT l_orderkey, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY l_orderkey HAVING sum(l_quantity) > 200")
sql("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, d):
    return t(spark, d, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, d):
    return t(spark, d, "orders", "o_orderstatus", "o_orderpriority").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS f, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM lineitem GROUP BY 1")
def agg_pivot(spark, d):
    p = t(spark, d, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("SELECT c_custkey, 'name' AS field, c_name AS value FROM customer UNION ALL SELECT c_custkey, 'segment', c_mktsegment FROM customer")
def agg_unpivot(spark, d):
    c = t(spark, d, "customer").select("c_custkey", F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment"))
    return c.unpivot("c_custkey", ["name", "segment"], "field", "value")


@query()
def agg_approx_distinct(spark, d):
    return t(spark, d, "lineitem", "l_partkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n"), F.count_distinct("l_partkey").alias("exact"))


@query()
def agg_approx_percentile(spark, d):
    return t(spark, d, "lineitem", "l_extendedprice").agg(F.percentile_approx("l_extendedprice", 0.5, 1000).alias("p50"))


@query()
def sketch_merge(spark, d):
    """Distinct counts by sketches of groups, merged."""
    per = t(spark, d, "lineitem", "l_returnflag", "l_suppkey").groupBy("l_returnflag").agg(F.hll_sketch_agg("l_suppkey").alias("s"))
    return per.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("n"))


# windows

sql("win_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
sql("win_ntile_percent_cume", "SELECT p_partkey, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_partkey)")
sql("win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
sql("win_first_last_nth", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS s FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
sql("win_running_sum", "SELECT l_orderkey, l_linenumber, round(sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber), 2) AS s FROM lineitem")
sql("win_rows_frame", "SELECT conv_id, turn, round(avg(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS m FROM conversations")
sql("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_custkey RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS n FROM orders")
sql("win_sessionize", """SELECT event_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT event_id, user_id, ts,
  CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL '30' MINUTE THEN 0 ELSE 1 END AS fresh FROM events) x""")

# order and sets


@query("SELECT n_name, lag(n_name) OVER (ORDER BY k NULLS LAST, n_name) AS before FROM (SELECT n_name, nullif(n_regionkey, 0) AS k FROM nation)")
def sort_nulls(spark, d):
    """nation has 25 rows by definition: one window over all of them."""
    n = t(spark, d, "nation").select("n_name", F.nullif("n_regionkey", F.lit(0)).alias("k"))
    return n.select("n_name", F.lag("n_name").over(Window.orderBy(F.asc_nulls_last("k"), "n_name")).alias("before"))


sql("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
sql("topk_per_group", "SELECT p_type, p_partkey FROM (SELECT p_type, p_partkey, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) x WHERE r <= 3")
sql("limit_offset", "SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5")


def _nations(spark, d):
    c = t(spark, d, "customer").select(F.col("c_nationkey").cast("long").alias("k"))
    return c, t(spark, d, "supplier").select(F.col("s_nationkey").cast("long").alias("k"))


_C, _S = "SELECT CAST(c_nationkey AS BIGINT) AS k FROM customer", "SELECT CAST(s_nationkey AS BIGINT) AS k FROM supplier"
for _n, _op, _f in (
    ("set_union_all", "UNION ALL", lambda a, b: a.union(b)),
    ("set_union_by_name", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("set_distinct", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(f"{_C} {_op} {_S}", name=_n)(lambda spark, d, f=_f: f(*_nations(spark, d)))

# functions

sql("fn_string_basic", "SELECT p_partkey, upper(p_name) AS u, substring(p_name, 1, 5) AS s, length(p_name) AS n, replace(p_brand, '#', '-') AS b, lpad(CAST(p_size AS STRING), 4, '0') AS z, reverse(p_brand) AS r FROM part", "SELECT p_partkey, upper(p_name) AS u, substring(p_name, 1, 5) AS s, length(p_name) AS n, replace(p_brand, '#', '-') AS b, lpad(CAST(p_size AS VARCHAR), 4, '0') AS z, reverse(p_brand) AS r FROM part")
sql("fn_regex", "SELECT page_id, regexp_extract(url, '//([^/]+)/', 1) AS host, regexp_replace(url, '[0-9]+', 'N') AS shape FROM pages", "SELECT page_id, regexp_extract(url, '//([^/]+)/', 1) AS host, regexp_replace(url, '[0-9]+', 'N', 'g') AS shape FROM pages")
sql("fn_split_explode", "SELECT w, count(*) AS n FROM (SELECT explode(split(text, ' ')) AS w FROM benchmark) x GROUP BY w", "SELECT w, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM benchmark) x GROUP BY w")
sql("fn_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS dist FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
sql("fn_hash_md5", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM documents", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
sql("fn_date_trunc_diff", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, datediff(o_orderdate, DATE '1992-01-01') AS days FROM orders", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
sql("fn_date_parts", "SELECT event_id, year(ts) AS y, month(ts) AS m, dayofmonth(ts) AS dd, hour(ts) AS h, quarter(ts) AS q FROM events", "SELECT event_id, year(ts) AS y, month(ts) AS m, day(ts) AS dd, hour(ts) AS h, quarter(ts) AS q FROM events")
sql("fn_interval_add", "SELECT o_orderkey, o_orderdate + INTERVAL '90' DAY AS due FROM orders")
sql("fn_math", "SELECT l_orderkey, l_linenumber, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS l, round(sqrt(l_extendedprice), 4) AS s, round(pow(l_quantity, 2), 2) AS p, CAST(abs(l_discount - 0.05) * 100 AS INT) AS a FROM lineitem", "SELECT l_orderkey, l_linenumber, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS l, round(sqrt(l_extendedprice), 4) AS s, round(pow(l_quantity, 2), 2) AS p, CAST(trunc(abs(l_discount - 0.05) * 100) AS INTEGER) AS a FROM lineitem")


@query(f"WITH {code_sql(16)} SELECT row_id, CAST(bit_count(code) AS INTEGER) AS ones, code << 1 AS l, code >> 3 AS r, xor(code, 255) AS x, code & 15 AS low FROM c")
def fn_bits(spark, d):
    c = F.col("code")
    return coded(spark, d, 16).select("row_id", F.bit_count(c).alias("ones"), F.shiftleft(c, 1).alias("l"), F.shiftright(c, 3).alias("r"), c.bitwiseXOR(F.lit(255)).alias("x"), c.bitwiseAND(F.lit(15)).alias("low"))


_V = "CAST(round(CAST(x AS DOUBLE) * 4096) AS BIGINT)"


@query(f"SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, list_transform(embedding, lambda x: {_V})[1] AS first FROM embeddings")
def fn_array_transform_filter(spark, d):
    return t(spark, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.get(V.quantize(F.col("embedding")), F.lit(0)).alias("first"))


@query(f"SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: {_V})) AS BIGINT) AS s, list_max(list_transform(embedding, lambda x: {_V})) AS m FROM embeddings")
def fn_array_aggregate(spark, d):
    q = V.quantize(F.col("embedding"))
    return t(spark, d, "embeddings").select("vec_id", F.aggregate(q, F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.array_max(q).alias("m"))


@query(f"SELECT vec_id, array_to_string(list_sort(list_transform(embedding, lambda x: {_V}))[1:5], ',') AS lowest FROM embeddings")
def fn_array_zip_sort(spark, d):
    return t(spark, d, "embeddings").select("vec_id", F.array_join(F.slice(F.array_sort(V.quantize(F.col("embedding"))), 1, 5).cast("array<string>"), ",").alias("lowest"))


@query(f"SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS pos, {_V} AS q FROM (SELECT vec_id, embedding, unnest(embedding) AS x, generate_subscripts(embedding, 1) FROM embeddings)".replace("generate_subscripts(embedding, 1) - 1 AS INTEGER) AS pos", "i - 1 AS INTEGER) AS pos").replace("generate_subscripts(embedding, 1) FROM", "generate_subscripts(embedding, 1) AS i FROM"))
def fn_array_explode_pos(spark, d):
    return t(spark, d, "embeddings").select("vec_id", F.posexplode(V.quantize(F.col("embedding"))).alias("pos", "q"))


@query(f"SELECT vec_id, array_to_string(list_transform(embedding, lambda x: {_V})[3:6], ' ') AS part FROM embeddings")
def fn_array_slice(spark, d):
    return t(spark, d, "embeddings").select("vec_id", F.array_join(F.slice(V.quantize(F.col("embedding")), 3, 4).cast("array<string>"), " ").alias("part"))


@query("SELECT o_orderkey, length(o_orderstatus) + length(o_orderpriority) AS total, upper(o_orderstatus) AS status FROM orders")
def fn_map_build_filter(spark, d):
    o = t(spark, d, "orders").select("o_orderkey", F.create_map(F.lit("status"), "o_orderstatus", F.lit("priority"), "o_orderpriority").alias("m"))
    up = F.transform_values("m", lambda k, v: F.upper(v))
    return o.select("o_orderkey", F.aggregate(F.map_values("m"), F.lit(0), lambda a, v: a + F.length(v)).alias("total"), F.element_at(F.map_filter(up, lambda k, v: k == "status"), "status").alias("status"))


@query("SELECT n_nationkey, n_name || '/' || CAST(n_regionkey AS VARCHAR) AS s FROM nation")
def fn_struct_nest(spark, d):
    n = t(spark, d, "nation").select("n_nationkey", F.struct("n_name", F.struct("n_regionkey").alias("r")).alias("x"))
    return n.select("n_nationkey", F.concat_ws("/", "x.n_name", F.col("x.r.n_regionkey").cast("string")).alias("s"))


sql("fn_json_extract", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")


@query("SELECT event_id, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) + 1 AS k FROM events")
def fn_json_roundtrip(spark, d):
    e = t(spark, d, "events").select("event_id", F.from_json("props", "k long").alias("p"))
    back = F.from_json(F.to_json(F.struct((F.col("p.k") + 1).alias("k"))), "k long")
    return e.select("event_id", back["k"].alias("k"))


# subqueries

sql("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
sql("sub_exists_correlated", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")
sql("sub_in", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)")
sql("sub_cte", "WITH per AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT n, count(*) AS customers FROM per GROUP BY n")
sql("sub_lateral", "SELECT c_custkey, x.o_orderkey FROM customer, LATERAL (SELECT max(o_orderkey) AS o_orderkey FROM orders WHERE o_custkey = c_custkey) x WHERE x.o_orderkey IS NOT NULL")

# dedup and iteration


@query("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY text")
def dedup_exact_text(spark, d):
    """Copies are counted by digest and length; the text itself is never shuffled."""
    x = t(spark, d, "documents").select("doc_id", F.sha2("text", 256).alias("h"), F.length("text").alias("n"))
    return x.groupBy("h", "n").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).select("doc_id", "copies")


@query("SELECT user_id, event_type, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts DESC, event_id DESC) AS r FROM events) x WHERE r = 1")
def dedup_keep_latest(spark, d):
    latest = F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id")
    return t(spark, d, "events").groupBy("user_id", "event_type").agg(latest)


@query(f"WITH RECURSIVE {code_sql(16)}{DEG_SQL}, n AS (SELECT DISTINCT site_id AS x, code % 1024 AS y FROM d), e AS (SELECT a.x AS x, b.x AS y FROM n a JOIN n b ON a.y = b.y AND a.x <> b.x), r(node, low) AS (SELECT x, least(x, y) FROM e UNION SELECT e.y, r.low FROM r JOIN e ON e.x = r.node) SELECT CAST(node AS BIGINT) AS node, CAST(min(low) AS BIGINT) AS component FROM r GROUP BY node")
def graph_components(spark, d):
    from ..operators.components import connected_components

    n = site_degrees(spark, d).select(F.col("site_id").alias("x"), (F.col("code") % 1024).alias("y")).distinct()
    low = n.groupBy("y").agg(F.min("x").alias("low"))
    return connected_components(n.join(low, "y").select(F.col("x").alias("src"), F.col("low").alias("dst")))


# user functions in SQL


@query(f"WITH {code_sql(16)} SELECT code AS cluster, truth, count(*) AS n FROM (SELECT code & 15 AS code, truth FROM c) GROUP BY ALL")
def udtf_code_counts(spark, d):
    from ..functions.udfs import register

    register(spark)
    return coded(spark, d, 16).select((F.col("code").bitwiseAND(F.lit(15))).alias("cluster"), "truth").groupBy("cluster", "truth").agg(F.count("*").alias("n"))


@query(f"WITH {code_sql(4)} SELECT DISTINCT code, CAST(xor(code, (1::BIGINT << CAST(b AS INTEGER))) AS BIGINT) AS neighbor FROM c, range(0, 4) t(b) UNION SELECT DISTINCT code, code FROM c")
def udtf_code_neighbors(spark, d):
    """Codes within one bit of each distinct code, by a table function."""
    from ..functions.udfs import register

    register(spark)
    codes = _labelled(spark, d).select(F.col("cluster").alias("code")).distinct()
    return spark.sql("SELECT c.code, n.neighbor FROM {codes} c, LATERAL code_neighbors(c.code, 4, 1) n", codes=codes)

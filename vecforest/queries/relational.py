"""The relational surface round the methods: scans, functions, joins, aggregations, windows, sorts and sets, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import exprs
from ..operators import views
from ..operators.views import queries_of, table
from ..plans.joins import asof_join, interval_join, salted_join
from . import sqlparts as sq
from .search import small_index

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
Q: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


# scans


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for t in TABLES:
        n = table(spark, sf_dir, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = n if out is None else out.unionByName(n)
    return out


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def scan_pruned(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_quantity")


@query("range_ids", "SELECT o_orderkey AS id, o_orderkey * o_orderkey % 97 AS m FROM orders")
def range_ids(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), (F.col("o_orderkey") * F.col("o_orderkey") % 97).alias("m"))


@query("scan_json")
def scan_json(spark, sf_dir):
    from ..plans.staging import shared_dir

    path = f"{shared_dir(spark)}/events-json"
    table(spark, sf_dir, "events").select("event_id", "user_id", "props").write.mode("overwrite").json(path)
    return spark.read.schema("event_id long, user_id long, props string").json(path)


@query("scan_fvecs")
def scan_fvecs(spark, sf_dir):
    from ..plans.staging import shared_dir
    from ..sources.vectors import VectorFiles, write_vectors

    path = f"{shared_dir(spark)}/vectors"
    write_vectors(views.emb64(spark, sf_dir), path)
    spark.dataSource.register(VectorFiles)
    return spark.read.format("vector_files").option("path", path).load()


@query("sql_knn", sq.with_(sq.VECTORS, sq.QUERIES, sq.PAIRS, sq.best(5, "d")) + "SELECT query_id, rank, vec_id FROM res")
def sql_knn(spark, sf_dir):
    exprs.register(spark)
    v = views.emb64(spark, sf_dir)
    v.createOrReplaceTempView("vf_points")
    queries_of(v).createOrReplaceTempView("vf_queries")
    return spark.sql(
        """SELECT query_id, rank, vec_id FROM (
             SELECT query_id, vec_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY round(dist, 9), vec_id) AS BIGINT) AS rank
             FROM (SELECT /*+ BROADCAST(q) */ query_id, vec_id, vf_l2(CAST(p.embedding AS ARRAY<DOUBLE>), CAST(q.embedding AS ARRAY<DOUBLE>)) AS dist FROM vf_points p JOIN vf_queries q ON vec_id <> query_id))
           WHERE rank <= :k""",
        args={"k": 5},
    )


# functions


@query("vec_functions", "WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), z AS (SELECT e AS z FROM v WHERE vec_id = 0) SELECT vec_id, round(list_dot_product(e, z), 6) AS dot, round(list_distance(e, z), 6) AS l2, round(list_sum([abs(e[i] - z[i]) FOR i IN range(1, 65)]), 6) AS l1, round(list_max([abs(e[i] - z[i]) FOR i IN range(1, 65)]), 6) AS linf, round(list_cosine_similarity(e, z), 6) AS cosine, round(sqrt(list_dot_product(e, e)), 6) AS norm FROM v, z")
def vec_functions(spark, sf_dir):
    v = views.emb64(spark, sf_dir).select("vec_id", exprs.doubles("embedding").alias("e"))
    z = F.broadcast(v.where("vec_id = 0").select(F.col("e").alias("z")))
    e, o = F.col("e"), F.col("z")
    r = lambda c: F.round(c, 6)
    return v.join(z).select("vec_id", r(exprs.dot(e, o)).alias("dot"), r(exprs.l2(e, o)).alias("l2"), r(exprs.l1(e, o)).alias("l1"), r(exprs.linf(e, o)).alias("linf"), r(exprs.cosine(e, o)).alias("cosine"), r(exprs.norm(e)).alias("norm"))


@query("array_functions", "WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) SELECT vec_id, round(list_min(e), 6) AS least, round(list_max(e), 6) AS most, CAST(len(list_filter(e, lambda x: x > 0)) AS INTEGER) AS positive, round(list_sum(e[1:8]), 6) AS head, round(list_sort(e)[32], 6) AS middle, list_max([abs(x) FOR x IN e]) > 0.3 AS spiky FROM v")
def array_functions(spark, sf_dir):
    e = F.col("e")
    v = views.emb64(spark, sf_dir).select("vec_id", exprs.doubles("embedding").alias("e"))
    return v.select(
        "vec_id", F.round(F.array_min(e), 6).alias("least"), F.round(F.array_max(e), 6).alias("most"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"),
        F.round(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda a, x: a + x), 6).alias("head"), F.round(F.element_at(F.array_sort(e), 32), 6).alias("middle"), F.exists(e, lambda x: F.abs(x) > 0.3).alias("spiky"),
    )


@query("code_bits", "SELECT p_partkey, p_size & 7 AS low, p_size >> 3 AS high, CAST(bit_count(p_size) AS INTEGER) AS ones, CAST(xor(p_size, 42) AS INTEGER) AS mixed, CAST((p_size & 1) | ((p_partkey & 1) << 1) | ((p_size & 2) << 1) | ((p_partkey & 2) << 2) AS BIGINT) AS woven FROM part")
def code_bits(spark, sf_dir):
    s, k = F.col("p_size"), F.col("p_partkey")
    bit = lambda c, m: c.bitwiseAND(F.lit(m).cast("long"))
    woven = bit(s.cast("long"), 1).bitwiseOR(F.shiftleft(bit(k, 1), 1)).bitwiseOR(F.shiftleft(bit(s.cast("long"), 2), 1)).bitwiseOR(F.shiftleft(bit(k, 2), 2))
    return table(spark, sf_dir, "part").select("p_partkey", s.bitwiseAND(7).alias("low"), F.shiftright(s, 3).alias("high"), F.bit_count(s).alias("ones"), s.bitwiseXOR(42).alias("mixed"), woven.alias("woven"))


@query("text_grams", "SELECT conv_id, turn, lower(substr(text, 1, 12)) AS head, CAST(length(text) AS INTEGER) AS n, CAST(len(list_distinct([substr(text, i, 3) FOR i IN range(1, length(text) - 1)])) AS INTEGER) AS grams, md5(text) AS digest, CAST(levenshtein(role, 'user') AS INTEGER) AS edits FROM conversations")
def text_grams(spark, sf_dir):
    t = F.col("text")
    n = F.length(t)
    grams = F.size(F.array_distinct(F.transform(F.when(n > 2, F.sequence(F.lit(1), n - 2)).otherwise(F.array().cast("array<int>")), lambda i: F.substr(t, i, F.lit(3)))))
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", F.lower(F.substring(t, 1, 12)).alias("head"), n.alias("n"), grams.alias("grams"), F.md5(t).alias("digest"), F.levenshtein("role", F.lit("user")).alias("edits"))


@query("time_features", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS hour, CAST(isodow(ts) AS INTEGER) AS dow, date_trunc('day', ts) AS day, epoch_us(ts) AS us, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days FROM events")
def time_features(spark, sf_dir):
    ts = F.col("ts")
    return table(spark, sf_dir, "events").select("event_id", F.hour(ts).alias("hour"), (F.weekday(ts) + 1).alias("dow"), F.date_trunc("day", ts).alias("day"), F.unix_micros(ts.cast("timestamp")).alias("us"), F.datediff(ts.cast("date"), F.lit("2024-01-01").cast("date")).alias("days"))


@query("math_functions", "SELECT event_id, round(sqrt(abs(value)), 6) AS root, round(ln(abs(value) + 1), 6) AS log, round(pow(value, 2), 4) AS square, CAST(floor(value) AS BIGINT) AS low, greatest(value, 50.0::DOUBLE) AS top, least(value, 50.0::DOUBLE) AS bottom, CAST(sign(value - 50) AS DOUBLE) AS side FROM events")
def math_functions(spark, sf_dir):
    v = F.col("value")
    return table(spark, sf_dir, "events").select("event_id", F.round(F.sqrt(F.abs(v)), 6).alias("root"), F.round(F.log1p(F.abs(v)), 6).alias("log"), F.round(F.pow(v, 2), 4).alias("square"), F.floor(v).alias("low"), F.greatest(v, F.lit(50.0)).alias("top"), F.least(v, F.lit(50.0)).alias("bottom"), F.signum(v - 50).alias("side"))


@query("json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, json_extract_string(props, '$.k') AS k_text FROM events")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("k_text"))


@query("sparse_vectors", "SELECT user_id, CAST(len(list(k)) AS INTEGER) AS dims, CAST(sum(n) AS BIGINT) AS total, max(n) AS most, round(sum(n * 0.5), 6)::DOUBLE AS half FROM (SELECT user_id, event_type AS k, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def sparse_vectors(spark, sf_dir):
    c = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # five event types
    vals = F.map_values("m")
    half = F.map_values(F.transform_values("m", lambda _, n: n * F.lit(0.5)))
    return m.select("user_id", F.size("m").alias("dims"), F.aggregate(vals, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.array_max(vals).alias("most"), F.round(F.aggregate(half, F.lit(0.0), lambda a, x: a + x), 6).alias("half"))


@query("one_hot", "SELECT c_custkey, CASE WHEN c_mktsegment = 'BUILDING' THEN 1 ELSE 0 END AS building, CASE WHEN c_mktsegment = 'MACHINERY' THEN 1 ELSE 0 END AS machinery, coalesce(nullif(c_nationkey, 0), -1) AS nation, c_acctbal IS NOT DISTINCT FROM NULL AS unknown, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'some' ELSE 'rich' END AS class FROM customer")
def one_hot(spark, sf_dir):
    hot = lambda s: F.when(F.col("c_mktsegment") == s, 1).otherwise(0)
    b = F.col("c_acctbal")
    return table(spark, sf_dir, "customer").select("c_custkey", hot("BUILDING").alias("building"), hot("MACHINERY").alias("machinery"), F.coalesce(F.nullif("c_nationkey", F.lit(0)), F.lit(-1)).alias("nation"), b.eqNullSafe(F.lit(None)).alias("unknown"), F.when(b < 0, "debt").when(b < 5000, "some").otherwise("rich").alias("class"))


@query("box_filter", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_discount BETWEEN 0.02 AND 0.05 AND l_tax IN (0.01, 0.02, 0.03) AND l_returnflag LIKE 'N%' AND l_shipdate IS NOT NULL")
def box_filter(spark, sf_dir):
    c = F.col
    return table(spark, sf_dir, "lineitem").where(c("l_quantity").between(10, 20) & c("l_discount").between(0.02, 0.05) & c("l_tax").isin(0.01, 0.02, 0.03) & c("l_returnflag").like("N%") & c("l_shipdate").isNotNull()).select("l_orderkey", "l_linenumber")


@query("page_hosts", r"SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, count(*) AS pages, count(*) FILTER (url LIKE 'https:%') AS secure FROM pages GROUP BY 1")
def page_hosts(spark, sf_dir):
    return table(spark, sf_dir, "pages").groupBy(F.parse_url(F.col("url"), F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("pages"), F.count_if(F.parse_url(F.col("url"), F.lit("PROTOCOL")) == "https").alias("secure"))


# joins


@query("join_broadcast", "SELECT n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark, sf_dir):
    n = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")  # 25 rows by definition
    return table(spark, sf_dir, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("join_sort_merge", "SELECT o_orderpriority, count(*) AS lines, CAST(sum(l_quantity) AS DOUBLE) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sort_merge(spark, sf_dir):
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_quantity").alias("quantity"))


@query("join_theta_leaf", sq.with_(sq.VECTORS, sq.QUERIES, "n AS (SELECT label, avg(e[1]) AS lo, avg(e[2]) AS hi FROM v GROUP BY label)") + "SELECT query_id, label FROM q JOIN n ON qe[1] >= round(lo, 9) AND qe[2] <= round(hi, 9)")
def join_theta_leaf(spark, sf_dir):
    v = views.emb64(spark, sf_dir).withColumn("e", exprs.doubles("embedding"))
    cells = v.groupBy("label").agg(F.round(F.avg(F.element_at("e", 1)), 9).alias("lo"), F.round(F.avg(F.element_at("e", 2)), 9).alias("hi"))
    q = v.where("vec_id % 100 = 0").select(F.col("vec_id").alias("query_id"), "e")
    return q.join(F.broadcast(cells), (F.element_at("e", 1) >= F.col("lo")) & (F.element_at("e", 2) <= F.col("hi"))).select("query_id", "label")  # ten labels


@query("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def join_semi(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@query("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


@query("join_range", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_range(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    left = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("first"))
    right = e.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("second"))
    return interval_join(left, right, ["user_id"], "ts", 3600).select("first", "second")


@query("join_asof", "SELECT a.event_id, b.event_id AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY user_id, ts) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def join_asof(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    left = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    right = e.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("before"))
    return asof_join(left, right, ["user_id"], "ts", ["before"]).select("event_id", "before")


@query("join_salted", "SELECT user_id, event_type, count(*) AS n FROM events JOIN (SELECT DISTINCT event_type AS t FROM events) ON event_type = t GROUP BY ALL")
def join_salted(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    kinds = e.select("event_type").distinct()
    return salted_join(e.select("user_id", "event_type"), kinds, ["event_type"], 8).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))


@query("diff_results", "SELECT coalesce(a.c_nationkey, b.s_nationkey) AS nation, a.c_nationkey IS NULL AS only_suppliers, b.s_nationkey IS NULL AS only_customers FROM (SELECT DISTINCT c_nationkey FROM customer WHERE c_acctbal > 9000) a FULL JOIN (SELECT DISTINCT s_nationkey FROM supplier WHERE s_acctbal > 5000) b ON c_nationkey = s_nationkey")
def diff_results(spark, sf_dir):
    a = table(spark, sf_dir, "customer").where("c_acctbal > 9000").select("c_nationkey").distinct()
    b = table(spark, sf_dir, "supplier").where("s_acctbal > 5000").select("s_nationkey").distinct()
    return a.join(b, F.col("c_nationkey") == F.col("s_nationkey"), "full").select(F.coalesce("c_nationkey", "s_nationkey").alias("nation"), F.col("c_nationkey").isNull().alias("only_suppliers"), F.col("s_nationkey").isNull().alias("only_customers"))


@query("lateral_topk", "SELECT c_custkey, o_orderkey, rank FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rank FROM customer JOIN orders ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING') WHERE rank <= 2")
def lateral_topk(spark, sf_dir):
    table(spark, sf_dir, "customer").createOrReplaceTempView("vf_customer")
    table(spark, sf_dir, "orders").createOrReplaceTempView("vf_orders")
    return spark.sql("""SELECT c_custkey, t.o_orderkey, CAST(t.pos + 1 AS BIGINT) AS rank FROM vf_customer,
      LATERAL (SELECT slice(array_sort(collect_list(struct(-o_totalprice AS p, o_orderkey))), 1, 2) AS best FROM vf_orders WHERE o_custkey = c_custkey),
      LATERAL (SELECT pos, col.o_orderkey FROM posexplode(best) AS x(pos, col)) t WHERE c_mktsegment = 'BUILDING'""")


# aggregation


@query("agg_basic", "SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS DOUBLE) AS sum_qty, round(avg(l_extendedprice), 4) AS avg_price, min(l_discount) AS least, max(l_tax) AS most, count(*) AS n FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("least"), F.max("l_tax").alias("most"), F.count(F.lit(1)).alias("n"))


@query("agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderstatus) AS states FROM orders GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderstatus").alias("states"))


@query("agg_approx")
def agg_approx(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.approx_count_distinct("o_custkey").alias("customers"), F.percentile_approx("o_totalprice", 0.5).alias("median"))


def _grouped(sql_by: str) -> str:
    return f"SELECT c_mktsegment, c_nationkey, count(*) AS n, CAST(grouping(c_mktsegment) * 2 + grouping(c_nationkey) AS BIGINT) AS g FROM customer GROUP BY {sql_by}"


@query("agg_rollup", _grouped("ROLLUP (c_mktsegment, c_nationkey)"))
def agg_rollup(spark, sf_dir):
    return table(spark, sf_dir, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))


@query("agg_cube", _grouped("CUBE (c_mktsegment, c_nationkey)"))
def agg_cube(spark, sf_dir):
    return table(spark, sf_dir, "customer").cube("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))


@query("agg_grouping_sets", _grouped("GROUPING SETS ((c_mktsegment), (c_nationkey), ())"))
def agg_grouping_sets(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupingSets([[F.col("c_mktsegment")], [F.col("c_nationkey")], []], "c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))


@query("agg_pivot", "SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '5-LOW') AS low FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    p = table(spark, sf_dir, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).agg(F.count(F.lit(1)))
    return p.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


@query("unpivot_features", "SELECT p_partkey, 'size' AS feature, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def unpivot_features(spark, sf_dir):
    p = table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "feature", "value")


@query("agg_min_by", "SELECT s_nationkey, arg_min(s_suppkey, (s_acctbal, s_suppkey)) AS poorest, arg_max(s_suppkey, (s_acctbal, s_suppkey)) AS richest FROM supplier GROUP BY 1")
def agg_min_by(spark, sf_dir):
    key = F.struct("s_acctbal", "s_suppkey")
    return table(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.min_by("s_suppkey", key).alias("poorest"), F.max_by("s_suppkey", key).alias("richest"))


@query("centroids", "SELECT label, CAST(i AS INTEGER) AS dim, round(avg(x), 6) AS mean FROM (SELECT label, unnest(CAST(embedding AS DOUBLE[])) AS x, unnest(range(0, 64)) AS i FROM embeddings) GROUP BY ALL")
def centroids(spark, sf_dir):
    return views.emb64(spark, sf_dir).select("label", F.posexplode(exprs.doubles("embedding")).alias("dim", "x")).groupBy("label", "dim").agg(F.round(F.avg("x"), 6).alias("mean"))


@query("agg_percentiles", "SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS q2, round(quantile_cont(value, 0.9), 6) AS q9 FROM events GROUP BY 1")
def agg_percentiles(spark, sf_dir):
    q = lambda x: F.round(F.percentile("value", F.lit(x)), 6)
    return table(spark, sf_dir, "events").groupBy("event_type").agg(q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.9).alias("q9"))


@query("agg_stats", "SELECT event_type, round(var_samp(value), 4) AS variance, round(stddev_pop(value), 4) AS deviation, round(corr(value, user_id), 6) AS correlation FROM events GROUP BY 1")
def agg_stats(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.var_samp("value"), 4).alias("variance"), F.round(F.stddev_pop("value"), 4).alias("deviation"), F.round(F.corr("value", "user_id"), 6).alias("correlation"))


@query("agg_filtered", "SELECT user_id, count(*) FILTER (value > 50) AS large, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY 1")
def agg_filtered(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.count_if(F.col("value") > 50).alias("large"), F.expr("count(*) FILTER (WHERE event_type = 'click')").alias("clicks"))


@query("agg_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 100 AND avg(l_quantity) > 20")
def agg_having(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"), F.avg("l_quantity").alias("q")).where("n > 100 AND q > 20").select("l_suppkey", "n")


# windows and sorts

_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


@query("win_ranking", f"SELECT o_orderkey, row_number() {_W} AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS BIGINT) AS dr, CAST(ntile(3) {_W} AS BIGINT) AS third, round(percent_rank() {_W}, 9) AS pr, round(cume_dist() {_W}, 9) AS cd FROM orders")
def win_ranking(spark, sf_dir):
    w, t = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderdate")
    big = lambda c: c.cast("long")
    return table(spark, sf_dir, "orders").select("o_orderkey", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(t)).alias("r"), big(F.dense_rank().over(t)).alias("dr"), big(F.ntile(3).over(w)).alias("third"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("win_analytic", f"SELECT o_orderkey, lag(o_totalprice) {_W} AS before, lead(o_totalprice, 1, 0.0) {_W} AS after, first_value(o_orderkey) {_W} AS first, nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM orders")
def win_analytic(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    every = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "orders").select("o_orderkey", F.lag("o_totalprice").over(w).alias("before"), F.lead("o_totalprice", 1, 0.0).over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"), F.nth_value("o_orderkey", 2).over(every).alias("second"))


@query("win_frames", f"SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS last3, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) // 1 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")
def win_frames(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    # DuckDB's // leaves the fraction of a DOUBLE: the frame ends between whole seconds
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    e = table(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("last3"), F.count(F.lit(1)).over(day).alias("day"))


@query("sort_ties", "SELECT l_orderkey, l_linenumber, l_discount FROM lineitem ORDER BY l_discount DESC NULLS LAST, l_orderkey, l_linenumber LIMIT 500")
def sort_ties(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_discount").orderBy(F.desc_nulls_last("l_discount"), "l_orderkey", "l_linenumber").limit(500)


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 10")
def topk_global(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(50)


@query("topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("range_sorted")
def range_sorted(spark, sf_dir):
    e = table(spark, sf_dir, "events").repartitionByRange(8, "ts").sortWithinPartitions("ts")
    return e.groupBy(F.spark_partition_id().alias("part")).agg(F.min("ts").alias("first"), F.max("ts").alias("last"), F.count(F.lit(1)).alias("n"))


@query("sampled_rows")
def sampled_rows(spark, sf_dir):
    return table(spark, sf_dir, "orders").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.1, "P": 0.5}, seed=1).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


# sets


@query("set_union", "SELECT c_nationkey AS nation, 'c' AS side FROM customer UNION SELECT s_nationkey, 's' FROM supplier")
def set_union(spark, sf_dir):
    a = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("nation"), F.lit("c").alias("side"))
    return a.unionByName(table(spark, sf_dir, "supplier").select(F.lit("s").alias("side"), F.col("s_nationkey").alias("nation"))).distinct()


@query("set_intersect", "SELECT c_nationkey AS nation FROM customer WHERE c_acctbal > 5000 INTERSECT SELECT s_nationkey FROM supplier")
def set_intersect(spark, sf_dir):
    return table(spark, sf_dir, "customer").where("c_acctbal > 5000").select(F.col("c_nationkey").alias("nation")).intersect(table(spark, sf_dir, "supplier").select("s_nationkey"))


@query("set_except", "SELECT o_custkey AS customer FROM orders EXCEPT SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING'")
def set_except(spark, sf_dir):
    builders = table(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    return table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("customer")).subtract(builders)


@query("view_sizes", "SELECT 'emb64' AS name, count(*) AS n, 64 AS d FROM embeddings UNION ALL SELECT 'doc_grams', count(*), 100 FROM documents UNION ALL SELECT 'conv_grams', count(*), 100 FROM conversations UNION ALL SELECT 'page_grams', count(*), 96 FROM pages UNION ALL SELECT 'line_num', count(*), 12 FROM lineitem UNION ALL SELECT 'user_series', count(DISTINCT user_id), 240 FROM events UNION ALL SELECT 'cust_profile', count(*), 19 FROM customer")
def view_sizes(spark, sf_dir):
    out = None
    for name, view in views.VIEWS.items():
        n = view(spark, sf_dir).agg(F.count(F.lit(1)).alias("n"), F.max(F.size("embedding")).alias("d")).select(F.lit(name).alias("name"), "n", "d")
        out = n if out is None else out.unionByName(n)
    return out


@query("code_bytes", "SELECT CAST(space AS INTEGER) AS space, count(*) AS n, CAST(count(*) * 4 AS BIGINT) AS bytes FROM embeddings, (SELECT unnest(range(1, 5)) AS space) GROUP BY space")
def code_bytes_(spark, sf_dir):
    from ..operators.range_query import code_bytes

    return code_bytes(small_index(spark, sf_dir)).groupBy("space").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("code")).cast("long").alias("bytes"))

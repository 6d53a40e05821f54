"""Relational operators around the methods, each with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from assetmill.operators import curriculum
from assetmill.plans.bounded import small_side
from assetmill.sources.tables import table as T

_J = F.col
#: Query vectors up to which they go to every executor; more are joined block by block.
SENT_VECTORS = 20_000


def scan_pushdown(s, d):
    return T(s, d, "lineitem").where(curriculum.scalar_filter({"l_quantity": {"min": 45}, "l_returnflag": {"include": ["A", "R"]}, "l_tax": {"max": 0.02}})).select("l_orderkey", "l_quantity", "l_returnflag")


def json_props(s, d):
    return T(s, d, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"))


def filter_mix(s, d):
    t = T(s, d, "documents")
    return t.where(_J("n_chars").between(100, 3000) & _J("lang").isin("en", "fr") & ~_J("source").like("src1_") & _J("text").rlike(r"\.\s")).select("doc_id", F.when(_J("n_chars") > 1000, "long").otherwise("short").alias("kind"), _J("source").eqNullSafe("src0").alias("first_source"))


def join_broadcast(s, d):
    return T(s, d, "lineitem").join(F.broadcast(T(s, d, "region").crossJoin(T(s, d, "nation")).where("r_regionkey = n_regionkey").select("n_nationkey", "r_name")), F.pmod(_J("l_suppkey"), F.lit(25)) == _J("n_nationkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


def joined(how: str):
    def run(s, d):
        li = T(s, d, "lineitem").select("l_orderkey", "l_quantity").hint(how)
        return T(s, d, "orders").join(li, _J("o_orderkey") == _J("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))

    return run


JOIN_SQL = "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def join_full(s, d):
    a = T(s, d, "customer").where("c_custkey % 3 <> 0").select("c_custkey")
    b = T(s, d, "orders").where("o_custkey % 2 = 0").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return a.join(b, _J("c_custkey") == _J("o_custkey"), "full").agg(F.count("c_custkey").alias("left_rows"), F.count("o_custkey").alias("right_rows"), F.count(F.lit(1)).alias("n"))


def semi_anti(how: str):
    return lambda s, d: T(s, d, "documents").join(T(s, d, "labels").where("toxic = 1"), "doc_id", how).select("doc_id", "source")


def join_range(s, d):
    """Prices into bands of 500 by an equi-join on the band, then the exact bounds."""
    bands = s.range(0, 10).select((_J("id") * 500).cast("double").alias("lo"), (_J("id") * 500 + 500).cast("double").alias("hi"), _J("id").alias("b"))
    p = T(s, d, "part").withColumn("bin", F.floor(_J("p_retailprice") / 500))
    return p.join(F.broadcast(bands), (_J("bin") == _J("b")) & (_J("p_retailprice") >= _J("lo")) & (_J("p_retailprice") < _J("hi"))).groupBy("lo").agg(F.count(F.lit(1)).alias("n"))


def join_asof(s, d):
    """Latest purchase of the user before each error, by one sorted pass over both kinds."""
    e = T(s, d, "events").where("event_type IN ('error', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last_value", F.last(F.when(_J("event_type") == "purchase", _J("value")), True).over(w)).where("event_type = 'error'").select("event_id", F.round("last_value", 6).alias("last_value"))


def join_interval(s, d):
    a = T(s, d, "events").where("event_type = 'error'").select("user_id", _J("ts").alias("t1"), _J("event_id").alias("e1"))
    b = T(s, d, "events").where("event_type = 'signup'").select(_J("user_id").alias("u2"), _J("ts").alias("t2"), _J("event_id").alias("e2"))
    return a.join(b, (_J("user_id") == _J("u2")) & (_J("t1") >= _J("t2")) & (_J("t1") <= _J("t2") + F.expr("INTERVAL 1 HOUR"))).select("e1", "e2")


def join_salted(s, d):
    """A hot key spread over eight salts."""
    li = T(s, d, "lineitem").select("l_suppkey", "l_extendedprice", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(8)).alias("salt"))
    su = T(s, d, "supplier").select("s_suppkey", "s_nationkey", F.explode(F.expr("sequence(0L, 7L)")).alias("salt2"))
    return li.join(su, (_J("l_suppkey") == _J("s_suppkey")) & (_J("salt") == _J("salt2"))).groupBy("s_nationkey").agg(F.round(F.sum("l_extendedprice"), 2).alias("price"))


def star(s, d):
    r = T(s, d, "lineitem").join(T(s, d, "orders"), _J("l_orderkey") == _J("o_orderkey")).join(T(s, d, "customer"), _J("o_custkey") == _J("c_custkey")).join(T(s, d, "nation"), _J("c_nationkey") == _J("n_nationkey")).join(T(s, d, "region"), _J("n_regionkey") == _J("r_regionkey")).join(T(s, d, "part"), _J("l_partkey") == _J("p_partkey"))
    return r.groupBy("r_name", "p_type").agg(F.round(F.sum(_J("l_extendedprice") * (1 - _J("l_discount"))), 2).alias("revenue"))


def agg_basic(s, d):
    return T(s, d, "lineitem").where("l_shipdate <= DATE '1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.sum(_J("l_extendedprice") * (1 - _J("l_discount"))), 2).alias("sum_disc_price"), F.round(F.avg("l_quantity"), 6).alias("avg_qty"), F.count(F.lit(1)).alias("n"))


def distinct(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days"))


def grouping(kind: str):
    def run(s, d):
        o = T(s, d, "orders").withColumn("y", F.year("o_orderdate"))
        g = o.rollup("o_orderstatus", "y") if kind == "rollup" else o.cube("o_orderstatus", "y")
        return g.agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    return run


GROUP_SQL = "SELECT o_orderstatus, year(o_orderdate)::INTEGER AS y, (grouping(o_orderstatus) * 2 + grouping(year(o_orderdate)))::BIGINT AS gid, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY {k} (o_orderstatus, year(o_orderdate))"


def grouping_sets(s, d):
    T(s, d, "orders").createOrReplaceTempView("gs_orders")
    return s.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM gs_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


def pivot(s, d):
    return T(s, d, "events").groupBy(F.to_date("ts").alias("day")).pivot("event_type", ["click", "error", "purchase", "signup", "view"]).count().na.fill(0)


def unpivot(s, d):
    return T(s, d, "part").groupBy("p_type").agg(F.min("p_size").cast("double").alias("lo"), F.max("p_size").cast("double").alias("hi")).unpivot("p_type", ["lo", "hi"], "which", "value")


def stats(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_discount"), 8).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"), F.bool_or(_J("l_tax") > 0.07).alias("any_high"), F.count_if(_J("l_discount") > 0.05).alias("deep"))


def quantiles(s, d):
    return T(s, d, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("p50"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


def collect(s, d):
    return T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names"))


def win_rank(s, d):
    w = Window.partitionBy("o_orderstatus").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return T(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(10).over(w).alias("tile"))


def win_lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return T(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.round(F.avg("value").over(w.rowsBetween(-3, 3)), 6).alias("around"), F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"))


def topk_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return T(s, d, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_brand", "p_partkey", "rn")


def sets(kind: str):
    def run(s, d):
        a = T(s, d, "orders").select(_J("o_custkey").alias("k")).where("k % 3 = 0")
        b = T(s, d, "customer").select(_J("c_custkey").alias("k")).where("k % 2 = 0")
        return {"union": a.union(b), "intersect": a.intersect(b), "except_all": a.exceptAll(b)}[kind].groupBy((_J("k") % 10).alias("m")).agg(F.count(F.lit(1)).alias("n"))

    return run


def set_sql(op: str) -> str:
    return f"SELECT k % 10 AS m, count(*) AS n FROM (SELECT o_custkey AS k FROM orders WHERE o_custkey % 3 = 0 {op} SELECT c_custkey FROM customer WHERE c_custkey % 2 = 0) GROUP BY 1"


def strings(s, d):
    return T(s, d, "pages").select("page_id", F.upper(F.substring("url", 1, 12)).alias("up"), F.md5("url").alias("md5"), F.levenshtein(F.substring("url", 1, 30), F.lit("https://www.example.com")).alias("lev"), F.lpad(_J("page_id").cast("string"), 8, "0").alias("pad"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.translate("url", "aeiou", "*****").alias("masked"))


def dates(s, d):
    return T(s, d, "orders").select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), F.datediff(F.lit("2000-01-01").cast("date"), F.to_date("o_orderdate")).cast("long").alias("days"), F.add_months(F.to_date("o_orderdate"), 2).alias("later"), F.dayofyear("o_orderdate").cast("long").alias("doy"))


def maths(s, d):
    x = _J("l_discount")
    return T(s, d, "lineitem").groupBy("l_linenumber").agg(F.round(F.sum(F.exp(x)), 4).alias("e"), F.round(F.sum(F.log1p(x)), 4).alias("l"), F.round(F.sum(F.tanh(x)), 4).alias("t"), F.sum(F.pmod(_J("l_orderkey"), F.lit(7))).alias("m"), F.max(F.greatest("l_discount", "l_tax")).alias("g"))


def arrays(s, d):
    a = F.transform("embedding", lambda x: x.cast("double"))
    return T(s, d, "embeddings").select("vec_id", F.round(F.aggregate(a, F.lit(0.0), lambda t, x: t + x), 5).alias("total"), F.size(F.filter(a, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.array_max(a), 6).alias("top"), F.exists(a, lambda x: x > 0.4).alias("peaky"))


def knn(s, d):
    """The three nearest vectors of each vector whose id is divisible by 100, against all, in blocks."""
    e = T(s, d, "embeddings").select("vec_id", _J("embedding").cast("array<double>").alias("v"))
    q = small_side(e.where("vec_id % 100 = 0").select(_J("vec_id").alias("q"), _J("v").alias("qv")), SENT_VECTORS)
    dot = F.aggregate(F.zip_with("v", "qv", lambda a, b: a * b), F.lit(0.0), lambda t, x: t + x)
    c = e.join(q, _J("q") != _J("vec_id")).select("q", "vec_id", F.round(dot, 6).alias("sim"))
    return c.withColumn("rn", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("sim"), "vec_id"))).where("rn <= 3")


def sample_hash(s, d):
    u = F.conv(F.substring(F.md5(_J("o_orderkey").cast("string")), 1, 8), 16, 10).cast("long")
    return T(s, d, "orders").where(u % 10 == 0).select("o_orderkey")


def subqueries(s, d):
    for t in ("orders", "customer"):
        T(s, d, t).createOrReplaceTempView(f"sq_{t}")
    return s.sql("SELECT c_custkey, (SELECT max(o_totalprice) FROM sq_orders WHERE o_custkey = c_custkey) AS best FROM sq_customer WHERE EXISTS (SELECT 1 FROM sq_orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")


QUERIES = {
    "op_scan_pushdown": (scan_pushdown, "SELECT l_orderkey, l_quantity, l_returnflag FROM lineitem WHERE l_quantity >= 45 AND l_returnflag IN ('A', 'R') AND l_tax <= 0.02"),
    "op_json_props": (json_props, "SELECT event_id, (props::JSON->>'k')::INTEGER AS k FROM events"),
    "op_filter_mix": (filter_mix, r"SELECT doc_id, CASE WHEN n_chars > 1000 THEN 'long' ELSE 'short' END AS kind, source IS NOT DISTINCT FROM 'src0' AS first_source FROM documents WHERE n_chars BETWEEN 100 AND 3000 AND lang IN ('en', 'fr') AND source NOT LIKE 'src1_' AND regexp_matches(text, '\.\s')"),
    "op_join_broadcast": (join_broadcast, "SELECT r_name, count(*) AS n FROM lineitem JOIN nation ON l_suppkey % 25 = n_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1"),
    "op_join_smj": (joined("merge"), JOIN_SQL),
    "op_join_shj": (joined("shuffle_hash"), JOIN_SQL),
    "op_join_full": (join_full, "SELECT count(c_custkey) AS left_rows, count(o_custkey) AS right_rows, count(*) AS n FROM (SELECT c_custkey FROM customer WHERE c_custkey % 3 <> 0) a FULL JOIN (SELECT o_custkey FROM orders WHERE o_custkey % 2 = 0 GROUP BY 1) b ON c_custkey = o_custkey"),
    "op_join_semi": (semi_anti("left_semi"), "SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)"),
    "op_join_anti": (semi_anti("left_anti"), "SELECT doc_id, source FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1)"),
    "op_join_range": (join_range, "SELECT floor(p_retailprice / 500) * 500.0::DOUBLE AS lo, count(*) AS n FROM part WHERE p_retailprice < 5000 GROUP BY 1"),
    "op_join_asof": (join_asof, "SELECT a.event_id, round(b.value, 6) AS last_value FROM (SELECT * FROM events WHERE event_type = 'error') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') b ON a.user_id = b.user_id AND a.ts >= b.ts"),
    "op_join_interval": (join_interval, "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'signup' AND a.ts BETWEEN b.ts AND b.ts + INTERVAL 1 HOUR"),
    "op_join_salted": (join_salted, "SELECT s_nationkey, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1"),
    "op_star_join": (star, "SELECT r_name, p_type, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
    "op_agg_basic": (agg_basic, "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS sum_disc_price, round(avg(l_quantity), 6) AS avg_qty, count(*) AS n FROM lineitem WHERE l_shipdate <= DATE '1998-09-02' GROUP BY 1, 2"),
    "op_distinct": (distinct, "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT ts::DATE) AS days FROM events GROUP BY 1"),
    "op_rollup": (grouping("rollup"), GROUP_SQL.format(k="ROLLUP")),
    "op_cube": (grouping("cube"), GROUP_SQL.format(k="CUBE")),
    "op_grouping_sets": (grouping_sets, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"),
    "op_pivot": (pivot, "SELECT ts::DATE AS day, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY 1"),
    "op_unpivot": (unpivot, "SELECT p_type, 'lo' AS which, min(p_size)::DOUBLE AS value FROM part GROUP BY 1 UNION ALL SELECT p_type, 'hi', max(p_size)::DOUBLE FROM part GROUP BY 1"),
    "op_agg_stats": (stats, "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 8) AS var, round(corr(l_quantity, l_extendedprice), 6) AS corr, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS dearest, bool_or(l_tax > 0.07) AS any_high, count(*) FILTER (l_discount > 0.05) AS deep FROM lineitem GROUP BY 1"),
    "op_quantiles": (quantiles, "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS p50, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1"),
    "op_agg_collect": (collect, "SELECT n_regionkey, string_agg(DISTINCT n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1"),
    "op_win_rank": (win_rank, "SELECT o_orderkey, row_number() OVER w AS rn, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(10) OVER w AS tile FROM orders WINDOW w AS (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey)"),
    "op_win_lag": (win_lag, "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 6) AS around, count(*) OVER w AS so_far FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "op_topk_group": (topk_group, "SELECT p_brand, p_partkey, rn FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) WHERE rn <= 3"),
    "op_topk": (lambda s, d: T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    "op_sort_offset": (lambda s, d: T(s, d, "orders").orderBy("o_orderdate", "o_orderkey").offset(100).limit(50).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 50 OFFSET 100"),
    "op_union": (sets("union"), set_sql("UNION ALL")),
    "op_intersect": (sets("intersect"), set_sql("INTERSECT")),
    "op_except_all": (sets("except_all"), set_sql("EXCEPT ALL")),
    "op_sample_hash": (sample_hash, "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT % 10 = 0"),
    "op_str": (strings, "SELECT page_id, upper(substr(url, 1, 12)) AS up, md5(url) AS md5, levenshtein(substr(url, 1, 30), 'https://www.example.com') AS lev, lpad(page_id::VARCHAR, 8, '0') AS pad, split_part(url, '/', 3) AS host, translate(url, 'aeiou', '*****') AS masked FROM pages"),
    "op_date": (dates, "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, date_diff('day', o_orderdate::DATE, DATE '2000-01-01') AS days, (o_orderdate::DATE + INTERVAL 2 MONTH)::DATE AS later, dayofyear(o_orderdate) AS doy FROM orders"),
    "op_math": (maths, "SELECT l_linenumber, round(sum(exp(l_discount)), 4) AS e, round(sum(ln(1 + l_discount)), 4) AS l, round(sum(tanh(l_discount)), 4) AS t, sum(l_orderkey % 7)::BIGINT AS m, max(greatest(l_discount, l_tax)) AS g FROM lineitem GROUP BY 1"),
    "op_array": (arrays, "SELECT vec_id, round(list_sum(embedding::DOUBLE[]), 5) AS total, len(list_filter(embedding::DOUBLE[], lambda x: x > 0)) AS positive, round(list_max(embedding::DOUBLE[]), 6) AS top, len(list_filter(embedding::DOUBLE[], lambda x: x > 0.4)) > 0 AS peaky FROM embeddings"),
    "op_knn_exact": (knn, "WITH c AS (SELECT q.vec_id AS q, e.vec_id, round(list_dot_product(e.embedding::DOUBLE[], q.embedding::DOUBLE[]), 6) AS sim FROM embeddings e JOIN embeddings q ON q.vec_id % 100 = 0 AND q.vec_id <> e.vec_id) SELECT * FROM (SELECT q, vec_id, sim, row_number() OVER (PARTITION BY q ORDER BY sim DESC, vec_id) AS rn FROM c) WHERE rn <= 3"),
    "op_subqueries": (subqueries, "SELECT c_custkey, (SELECT max(o_totalprice) FROM orders WHERE o_custkey = c_custkey) AS best FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')"),
}

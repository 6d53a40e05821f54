"""Other file formats, table functions, cogrouped functions and approximate neighbours."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from assetmill.operators import mathkit
from assetmill.plans.scratch import Scratch
from assetmill.plans.ship import ship
from assetmill.sources.tables import table
from assetmill.workloads.curation import ASSETS_SQL
from assetmill.workloads.relational import JOIN_SQL


def round_trip(kind: str, **options):
    """Parts written in another format to the shared folder and read back with their schema."""

    def run(s, d):
        p = table(s, d, "part").select("p_partkey", "p_name", "p_size", "p_retailprice")
        with Scratch(s, f"src-{kind}") as scratch:
            at = scratch.path(kind)
            p.write.format(kind).options(**options).save(at)
            return s.read.format(kind).schema(p.schema).options(**options).load(at)

    return run


PART_SQL = "SELECT p_partkey, p_name, p_size, p_retailprice FROM part"


class Lines:
    """Cuts a text into lines of a fixed width."""

    def eval(self, text: str, width: int):
        for n, at in enumerate(range(0, len(text or ""), width)):
            yield n, text[at : at + width]


def glyph_lines(s, d):
    ship(s)
    f = F.udtf(Lines, returnType="line_no int, line string")
    return table(s, d, "part").select("p_partkey", "p_name").lateralJoin(f(F.col("p_name").outer(), F.lit(8))).select("p_partkey", "line_no", "line")


def cogrouped(s, d):
    """Suppliers beside customers of each nation; both sides come as one row a nation, so a group is two rows."""
    ship(s)
    side = lambda t, p: table(s, d, t).groupBy(F.col(f"{p}_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n"))

    def both(left, right):
        import pandas as pd

        key = (left if len(left) else right)["nation"].iloc[0]
        return pd.DataFrame({"nation": [key], "suppliers": [int(left["n"].sum())], "customers": [int(right["n"].sum())]})

    return side("supplier", "s").groupBy("nation").cogroup(side("customer", "c").groupBy("nation")).applyInPandas(both, "nation int, suppliers long, customers long")


BANDS, BITS, NEAREST = 20, 4, 5


def band_codes(df, dims: int = 64, seed: int = 7):
    """Codes of each vector: signs of ``BITS`` random directions a band."""
    ship(df.sparkSession)
    schema = pa.schema([pa.field("vec_id", pa.int64()), pa.field("codes", pa.list_(pa.int32()))])

    def run(batches):
        planes = np.random.default_rng(seed).standard_normal((dims, BANDS * BITS))
        for b in batches:
            if b.num_rows:
                bits = (np.array(b.column(1).to_pylist(), dtype=np.float64) @ planes > 0).reshape(b.num_rows, BANDS, BITS)
                codes = (bits * (1 << np.arange(BITS))).sum(axis=2).astype(np.int32)
                yield pa.record_batch([b.column(0), pa.array(list(codes), pa.list_(pa.int32()))], schema=schema)

    return df.select("vec_id", "embedding").mapInArrow(run, "vec_id long, codes array<int>")


def knn_lsh(s, d):
    """Five nearest by cosine, for every hundredth vector, among those that share a band; the rest is not looked at.
    Unrelated vectors share one of the bands in about 7 of 10 cases, so this saves little unless neighbours are close
    enough for fewer bands of more bits."""
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    coded = band_codes(table(s, d, "embeddings")).select("vec_id", F.posexplode("codes").alias("band", "code"))
    q = coded.where("vec_id % 100 = 0").withColumnRenamed("vec_id", "q")
    pairs = q.join(coded, ["band", "code"]).where("q <> vec_id").select("q", "vec_id").distinct()
    x = pairs.join(e, "vec_id").join(e.select(F.col("vec_id").alias("q"), F.col("x").alias("y")), "q")
    cos = mathkit.dot(F.col("x"), F.col("y")) / F.sqrt(mathkit.dot(F.col("x"), F.col("x")) * mathkit.dot(F.col("y"), F.col("y")))
    w = Window.partitionBy("q").orderBy(F.desc("cosine"), "vec_id")
    return x.select("q", "vec_id", F.round(cos, 6).alias("cosine")).withColumn("place", F.row_number().over(w)).where(F.col("place") <= NEAREST)


# --- scans, sinks and sources -----------------------------------------------------------------------


def partition_prune(s, d):
    """A snapshot partitioned by tier, of which one tier is read."""
    from assetmill.operators import catalog
    from assetmill.workloads.curation import assets

    with Scratch(s, "prune") as scratch:
        path = catalog.publish(assets(s, d).select("doc_id", "width", "quality_tier"), scratch.root, 1)
    return s.read.parquet(path).where("quality_tier = 4").select("doc_id", "width")


def bucketed(s, d):
    """Orders and lines written in equal buckets by order, joined without an exchange of either."""
    import uuid

    tag = uuid.uuid4().hex[:10]
    with Scratch(s, "bucketed") as scratch:
        for t, key, cols in (("orders", "o_orderkey", ["o_orderkey", "o_orderstatus"]), ("lineitem", "l_orderkey", ["l_orderkey", "l_quantity"])):
            rows = table(s, d, t).select(*cols)
            rows.write.bucketBy(8, key).sortBy(key).format("parquet").option("maxRecordsPerFile", 1_000_000).option("path", scratch.path(t)).saveAsTable(f"{t}_{tag}")
    o, li = s.table(f"orders_{tag}"), s.table(f"lineitem_{tag}").hint("merge")
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


def text_files(s, d):
    """Part names as a text file, read back line by line."""
    with Scratch(s, "src-text") as scratch:
        table(s, d, "part").select("p_name").write.text(scratch.path("names"))
        return s.read.text(scratch.path("names")).groupBy("value").agg(F.count(F.lit(1)).alias("n"))


def binary_files(s, d):
    """Files as bytes: how many, and that each one's stated length is its content's."""
    with Scratch(s, "src-binary") as scratch:
        table(s, d, "part").select("p_name").repartition(3).write.text(scratch.path("names"))
        files = s.read.format("binaryFile").option("pathGlobFilter", "*.txt").load(scratch.path("names"))
        return files.agg(F.count(F.lit(1)).alias("files"), F.sum(F.length("content")).cast("long").alias("bytes"), F.count_if(F.length("content") != F.col("length")).alias("odd"))


class CropSource(DataSource):
    """Crop sizes of a base resolution as a table, one partition a base: ``spark.read.format("crops")``."""

    @classmethod
    def name(cls):
        return "crops"

    def schema(self):
        return "base int, w int, h int"

    def reader(self, schema):
        return CropReader(self.options)


class CropReader(DataSourceReader):
    def __init__(self, options):
        self.bases = [int(b) for b in options.get("bases", "256").split(",")]

    def partitions(self):
        return [InputPartition(b) for b in self.bases]

    def read(self, partition):
        from assetmill.operators import curriculum

        for w, h in curriculum.crops(partition.value):
            yield partition.value, w, h


def python_source(s, d):
    """Crop sizes of the source, each with the lines whose quantity is its width in steps of 64."""
    ship(s)
    s.dataSource.register(CropSource)
    lines = table(s, d, "lineitem").groupBy((F.col("l_quantity").cast("int") * 64).alias("side")).agg(F.count(F.lit(1)).alias("lines"))
    c = s.read.format("crops").option("bases", "256,512,1024").load()
    return c.join(lines, F.col("w") == F.col("side"), "left").select("base", "w", "h", F.coalesce("lines", F.lit(0)).alias("lines"))


# --- relational and functions -----------------------------------------------------------------------


def html_fields(s, d):
    """Fields of a page by patterns: title, language, links."""
    p = table(s, d, "pages")
    return p.select("page_id", F.regexp_extract("html", "(?s)<title>(.*?)</title>", 1).alias("title"), F.regexp_extract("html", 'lang="([a-z]+)"', 1).alias("lang"), F.regexp_count("html", F.lit("<a ")).cast("long").alias("links"), F.regexp_count("html", F.lit("<p>")).cast("long").alias("paragraphs"))


def sql_surface(s, d):
    """A method's output as a view, asked in SQL."""
    from assetmill.workloads.curation import assets

    assets(s, d).select("media_source", "quality_tier", "width").createOrReplaceTempView("surface_assets")
    return s.sql("SELECT media_source, quality_tier, count(*) AS n, max(width) AS widest FROM surface_assets GROUP BY ALL HAVING count(*) > 1")


def join_theta(s, d):
    """Parts in overlapping price windows by a condition that is no equality, over a bounded table of windows."""
    windows = s.range(0, 12).select((F.col("id") * 150 + 800).cast("double").alias("lo"), (F.col("id") * 150 + 1200).cast("double").alias("hi"))
    p = table(s, d, "part").select("p_retailprice")
    return p.join(F.broadcast(windows), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("lo").agg(F.count(F.lit(1)).alias("n"))


def lateral(s, d):
    """The dearest order of each customer by a lateral subquery."""
    table(s, d, "customer").createOrReplaceTempView("lt_customer")
    table(s, d, "orders").createOrReplaceTempView("lt_orders")
    return s.sql("SELECT c_custkey, b.best FROM lt_customer, LATERAL (SELECT max(o_totalprice) AS best FROM lt_orders WHERE o_custkey = c_custkey) b WHERE b.best IS NOT NULL")


def win_frames(s, d):
    """Running sum, sum over the last three days by range, and mean over rows around."""
    o = table(s, d, "orders").withColumn("day", F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date")))
    by = Window.partitionBy("o_custkey").orderBy("day", "o_orderkey")
    days = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-3, 0)
    return o.select("o_orderkey", F.round(F.sum("o_totalprice").over(by.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("so_far"), F.round(F.sum("o_totalprice").over(days), 2).alias("three_days"), F.round(F.avg("o_totalprice").over(by.rowsBetween(-1, 1)), 4).alias("around"))


def maps(s, d):
    """Counts by kind as a map, filtered, changed and taken apart again."""
    m = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    more = F.map_concat(F.map_filter("m", lambda k, v: k != "view"), F.create_map(F.lit("all"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda t, v: t + v)))
    return m.select("user_id", F.explode(F.transform_values(more, lambda k, v: v * 2)).alias("kind", "twice"))


def json_fields(s, d):
    """Structs to text and back, and single fields by path."""
    e = table(s, d, "events").select("event_id", F.to_json(F.struct(F.col("event_type").alias("t"), F.struct("user_id").alias("who"))).alias("j"))
    back = F.from_json("j", "t STRING, who STRUCT<user_id: BIGINT>")
    return e.select("event_id", F.get_json_object("j", "$.t").alias("t"), back["who"]["user_id"].alias("user_id"), F.json_object_keys("j")[1].alias("second"))


def pandas_scalar(s, d):
    ship(s)

    @F.pandas_udf("double")
    def relative(v, top):
        return (v / top).round(6)

    return table(s, d, "part").select("p_partkey", relative(F.col("p_retailprice"), F.lit(2000.0)).alias("relative"))


def arrow_scalar(s, d):
    ship(s)

    @F.arrow_udf("long")
    def doubled(v: pa.Array) -> pa.Array:
        import pyarrow.compute as pc

        return pc.multiply(pc.cast(v, "int64"), 2)

    return table(s, d, "part").select("p_partkey", doubled(F.col("p_size")).alias("twice"))


def pandas_iterator(s, d):
    """A function that keeps a table of its own over all batches of a task."""
    ship(s)

    def run(batches):
        import pandas as pd

        names = {k: f"size {k}" for k in range(1, 101)}
        for v in batches:
            yield pd.Series([names.get(int(x)) for x in v], dtype=object)

    from collections.abc import Iterator

    import pandas as pd

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return table(s, d, "part").select("p_partkey", F.pandas_udf(run, "string")(F.col("p_size")).alias("size_name"))


def pandas_grouped(s, d):
    """A group's middle value by a function of whole groups; nations bound them to a few hundred suppliers a thousandth."""
    import pandas as pd

    ship(s)

    def middle(v):
        return float(v.median())

    middle.__annotations__ = {"v": pd.Series, "return": float}
    return table(s, d, "supplier").groupBy("s_nationkey").agg(F.round(F.pandas_udf(middle, "double")("s_acctbal"), 4).alias("middle"))


def sql_function(s, d):
    """A function defined in SQL, inlined into the plan."""
    table(s, d, "part").createOrReplaceTempView("fn_part")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION price_band(p DOUBLE) RETURNS STRING RETURN CASE WHEN p < 1200 THEN 'low' WHEN p < 1600 THEN 'middle' ELSE 'high' END")
    return s.sql("SELECT price_band(p_retailprice) AS band, count(*) AS n FROM fn_part GROUP BY 1")


QUERIES = {
    "src_csv": (round_trip("csv", header="true"), PART_SQL),
    "src_json": (round_trip("json"), PART_SQL),
    "src_orc": (round_trip("orc"), PART_SQL),
    "src_xml": (round_trip("xml", rowTag="part"), PART_SQL),
    "udf_lines": (glyph_lines, "SELECT p_partkey, k::INTEGER AS line_no, substr(p_name, k * 8 + 1, 8) AS line FROM part, range(100) t(k) WHERE k * 8 < length(p_name)"),
    "udf_cogroup": (cogrouped, "SELECT nation, coalesce(suppliers, 0) AS suppliers, coalesce(customers, 0) AS customers FROM (SELECT s_nationkey AS nation, count(*) AS suppliers FROM supplier GROUP BY 1) FULL JOIN (SELECT c_nationkey AS nation, count(*) AS customers FROM customer GROUP BY 1) USING (nation)"),
    "op_knn_lsh": (knn_lsh, None),
    "op_partition_prune": (partition_prune, ASSETS_SQL + "SELECT doc_id, width FROM assets WHERE quality_tier = 4"),
    "sink_bucketed": (bucketed, JOIN_SQL),
    "src_text": (text_files, "SELECT p_name AS value, count(*) AS n FROM part GROUP BY 1"),
    "src_binary": (binary_files, "SELECT least(3, count(*)) AS files, sum(strlen(p_name) + 1)::BIGINT AS bytes, 0::BIGINT AS odd FROM part"),
    "src_python": (python_source, "SELECT b.base::INTEGER AS base, (w * 64)::INTEGER AS w, (h * 64)::INTEGER AS h, coalesce(n, 0) AS lines FROM (VALUES (256), (512), (1024)) b(base), range(1, 257) x(w), range(1, 257) y(h) LEFT JOIN (SELECT l_quantity::INTEGER AS q, count(*) AS n FROM lineitem GROUP BY 1) l ON l.q = w WHERE w * h * 4096 <= base * base AND w * h * 4096 >= 0.5 * base * base AND greatest(w, h) <= 4 * least(w, h)"),
    "op_html_fields": (html_fields, """SELECT page_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS title, regexp_extract(html, 'lang="([a-z]+)"', 1) AS lang, len(regexp_extract_all(html, '<a '))::BIGINT AS links, len(regexp_extract_all(html, '<p>'))::BIGINT AS paragraphs FROM pages"""),
    "op_sql_surface": (sql_surface, ASSETS_SQL + "SELECT media_source, quality_tier, count(*) AS n, max(width) AS widest FROM assets GROUP BY 1, 2 HAVING count(*) > 1"),
    "op_join_theta": (join_theta, "SELECT (i * 150 + 800)::DOUBLE AS lo, count(*) AS n FROM part JOIN range(12) t(i) ON p_retailprice >= i * 150 + 800 AND p_retailprice < i * 150 + 1200 GROUP BY 1"),
    "op_lateral": (lateral, "SELECT o_custkey AS c_custkey, max(o_totalprice) AS best FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"),
    "op_win_frames": (win_frames, "WITH o AS (SELECT *, date_diff('day', DATE '1990-01-01', o_orderdate::DATE) AS day FROM orders) SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY day, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS so_far, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 3 PRECEDING AND CURRENT ROW), 2) AS three_days, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY day, o_orderkey ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS around FROM o"),
    "op_map": (maps, "SELECT user_id, event_type AS kind, 2 * count(*) AS twice FROM events WHERE event_type <> 'view' GROUP BY 1, 2 UNION ALL SELECT user_id, 'all', 2 * count(*) FROM events GROUP BY 1"),
    "op_json": (json_fields, "SELECT event_id, event_type AS t, user_id, 'who' AS second FROM events"),
    "udf_pandas_scalar": (pandas_scalar, "SELECT p_partkey, round(p_retailprice / 2000, 6) AS relative FROM part"),
    "udf_arrow_scalar": (arrow_scalar, "SELECT p_partkey, 2 * p_size::BIGINT AS twice FROM part"),
    "udf_pandas_iterator": (pandas_iterator, "SELECT p_partkey, 'size ' || p_size::VARCHAR AS size_name FROM part"),
    "udf_pandas_grouped": (pandas_grouped, "SELECT s_nationkey, round(median(s_acctbal), 4) AS middle FROM supplier GROUP BY 1"),
    "udf_sql_function": (sql_function, "SELECT CASE WHEN p_retailprice < 1200 THEN 'low' WHEN p_retailprice < 1600 THEN 'middle' ELSE 'high' END AS band, count(*) AS n FROM part GROUP BY 1"),
}

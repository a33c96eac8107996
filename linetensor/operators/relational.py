"""Relational operators that the methods stand on, each as a small query with its DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import read_table
from ..sources.workloads import WORKLOADS

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None) -> Callable:
    def keep(function: Callable[[SparkSession, str], DataFrame]) -> Callable:
        QUERIES[function.__name__] = function
        if sql:
            ORACLES[function.__name__] = sql
        return function

    return keep


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, bucket_seconds: int) -> DataFrame:
    """For each left row the right row of the same key at or before its time, the latest one.

    Both sides become one stream per key and time bucket, so a busy key is cut into buckets; each
    bucket is carried the last right row before it.
    """
    slot = F.floor(F.unix_micros(F.col(at).cast("timestamp")) / (bucket_seconds * 1_000_000)).alias("slot")
    rights = right.select(by, at, value, slot)
    last = rights.groupBy(by, "slot").agg(F.max(F.struct(at, value)).alias("last"))
    carried = last.select(by, F.lead("slot").over(Window.partitionBy(by).orderBy("slot")).alias("until"), "slot", "last")
    lefts = left.withColumn("slot", slot).withColumn("__id", F.monotonically_increasing_id())
    inside = lefts.alias("l").join(rights.alias("r"), [by, "slot"]).where(F.col(f"r.{at}") <= F.col(f"l.{at}"))
    inside = inside.groupBy("__id").agg(F.max(F.struct(F.col(f"r.{at}"), F.col(f"r.{value}"))).alias("inside"))
    before = lefts.join(carried.select(F.col(by).alias("__by"), F.col("slot").alias("__from"), "until", "last"), (F.col(by) == F.col("__by")) & (F.col("__from") < F.col("slot")) & (F.col("until").isNull() | (F.col("until") >= F.col("slot"))), "left").select(*left.columns, "__id", "last")
    found = before.join(inside, "__id", "left").withColumn("match", F.coalesce("inside", "last"))
    return found.select(*left.columns, F.col(f"match.{value}").alias(f"asof_{value}"))


def range_join(points: DataFrame, at: str, spans: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Points with the spans that hold them: spans are dealt to buckets of the given width, so the join is by equality."""
    dealt = spans.withColumn("bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("bucket", F.floor(F.col(at) / width)).join(dealt, "bucket").where(F.col(at).between(F.col(lo), F.col(hi))).drop("bucket")


@query("SELECT e.event_id, e.user_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS asof_purchase FROM events e WHERE e.event_type = 'click'")
def asof_events(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    clicks, bought = e.where("event_type = 'click'"), e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    return asof_join(clicks.select("event_id", "user_id", "ts"), bought, "user_id", "ts", "purchase", 86_400 * 3).drop("ts")


@query("SELECT o_orderkey, band FROM orders JOIN (SELECT unnest(range(0, 400)) AS band) ON o_totalprice BETWEEN band * 1000 AND band * 1000 + 999")
def range_join_price_bands(spark: SparkSession, d: str) -> DataFrame:
    bands = spark.range(400).select(F.col("id").alias("band"), (F.col("id") * 1000).alias("lo"), (F.col("id") * 1000 + 999).alias("hi"))
    return range_join(read_table(spark, d, "orders", "o_orderkey", "o_totalprice"), "o_totalprice", bands, "lo", "hi", 1000).select("o_orderkey", "band")


@query("SELECT DISTINCT token FROM (SELECT unnest(regexp_split_to_array(text, '[ \n]+')) AS token FROM benchmark) WHERE token <> '' AND token NOT IN (SELECT unnest(regexp_split_to_array(text, '[ \n]+')) FROM documents)")
def dict_antijoin(spark: SparkSession, d: str) -> DataFrame:
    words = lambda n: read_table(spark, d, n, "text").select(F.explode(F.split("text", "[ \n]+")).alias("token")).where("token <> ''").distinct()
    return words("benchmark").join(words("documents"), "token", "left_anti")


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def semi_join_customers(spark: SparkSession, d: str) -> DataFrame:
    orders = read_table(spark, d, "orders", "o_custkey", "o_orderstatus").where("o_orderstatus = 'F'")
    return read_table(spark, d, "customer", "c_custkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def outer_join_counts(spark: SparkSession, d: str) -> DataFrame:
    orders = read_table(spark, d, "orders", "o_custkey", "o_orderkey")
    return read_table(spark, d, "customer", "c_custkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


_MARGIN = "c_nationkey, b, year(l_shipdate) AS y, l_quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN (SELECT p_partkey, p_brand AS b FROM part) ON l_partkey = p_partkey"


def _margin_rows(spark: SparkSession, d: str) -> DataFrame:
    return WORKLOADS["w09"].build(spark, d)


def _grouping_sql(kind: str) -> str:
    return f"SELECT c1, c2, c4, grouping(c1, c2, c4)::BIGINT AS level, sum(val) AS total FROM ({WORKLOADS['w09'].sql}) GROUP BY {kind}"


@query(_grouping_sql("CUBE (c1, c2, c4)"))
def marginals_cube(spark: SparkSession, d: str) -> DataFrame:
    return _margin_rows(spark, d).cube("c1", "c2", "c4").agg(F.grouping_id().cast("long").alias("level"), F.sum("val").alias("total"))


@query(_grouping_sql("ROLLUP (c1, c2, c4)"))
def marginals_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _margin_rows(spark, d).rollup("c1", "c2", "c4").agg(F.grouping_id().cast("long").alias("level"), F.sum("val").alias("total"))


@query(_grouping_sql("GROUPING SETS ((c1), (c2, c4), ())"))
def marginals_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    _margin_rows(spark, d).createOrReplaceTempView("__w09")
    return spark.sql("SELECT c1, c2, c4, CAST(grouping_id(c1, c2, c4) AS BIGINT) AS level, sum(val) AS total FROM __w09 GROUP BY GROUPING SETS ((c1), (c2, c4), ())")


@query(f"SELECT c1, n FROM (SELECT c1, count(*) AS n FROM ({WORKLOADS['w01'].sql}) GROUP BY c1) ORDER BY n DESC, c1 LIMIT 20")
def topk_slices(spark: SparkSession, d: str) -> DataFrame:
    return WORKLOADS["w01"].build(spark, d).groupBy("c1").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "c1").limit(20)


@query(f"SELECT c2, c1, val FROM (SELECT c2, c1, sum(val) AS val, row_number() OVER (PARTITION BY c2 ORDER BY sum(val) DESC, c1) AS k FROM ({WORKLOADS['w01'].sql}) GROUP BY c2, c1) WHERE k <= 3")
def topk_per_group(spark: SparkSession, d: str) -> DataFrame:
    rows = WORKLOADS["w01"].build(spark, d).groupBy("c2", "c1").agg(F.sum("val").alias("val"))
    return rows.withColumn("k", F.row_number().over(Window.partitionBy("c2").orderBy(F.desc("val"), "c1"))).where("k <= 3").drop("k")


_SETS = {"intersect": "INTERSECT", "except": "EXCEPT", "union": "UNION"}
for _name, _word in _SETS.items():
    _a, _b = (f"SELECT c1, c2, c3 FROM ({WORKLOADS[n].sql})" for n in ("w03", "w01"))
    _sql = f"{_a} {_word} {_b}" if _name != "except" else f"{_b} {_word} {_a}"

    def _run(spark: SparkSession, d: str, name: str = _name) -> DataFrame:
        a, b = (WORKLOADS[n].build(spark, d).select("c1", "c2", "c3") for n in ("w03", "w01"))
        return {"intersect": lambda: a.intersect(b), "except": lambda: b.exceptAll(a), "union": lambda: a.union(b).distinct()}[name]()

    QUERIES[f"coo_{_name}"], ORACLES[f"coo_{_name}"] = _run, _sql


@query("SELECT user_id, event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr, ntile(4) OVER w AS quarter, lag(event_id) OVER w AS previous, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS last_three FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def windows_events(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", "user_id", "event_id", "ts", "event_type")
    w, t = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id").orderBy("event_type")
    return e.select("user_id", "event_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(t).cast("long").alias("rk"), F.dense_rank().over(t).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"), F.lag("event_id").over(w).alias("previous"), F.sum("event_id").over(w.rowsBetween(-2, 0)).alias("last_three"))


@query("SELECT user_id, coalesce(sum(1) FILTER (event_type = 'click'), 0)::BIGINT AS click, coalesce(sum(1) FILTER (event_type = 'view'), 0)::BIGINT AS view FROM events GROUP BY user_id")
def pivot_events(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", "user_id", "event_type")
    return e.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT idx, r, v FROM (SELECT idx, unnest(range(3)) AS r, CASE unnest(range(3)) WHEN 0 THEN idx * 0.5 WHEN 1 THEN idx * 1.5 ELSE idx * 2.5 END::DOUBLE AS v FROM (SELECT DISTINCT l_partkey AS idx FROM lineitem WHERE l_partkey IS NOT NULL))")
def unpivot_factor(spark: SparkSession, d: str) -> DataFrame:
    """A factor of the part mode, with a row for every part that lineitem has, from columns to entries."""
    parts = read_table(spark, d, "lineitem", F.col("l_partkey").alias("idx")).where("idx IS NOT NULL").distinct()
    wide = parts.select("idx", *[(F.col("idx") * k).cast("double").alias(str(r)) for r, k in enumerate((0.5, 1.5, 2.5))])
    return wide.unpivot("idx", ["0", "1", "2"], "r", "v").withColumn("r", F.col("r").cast("long"))


@query("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber FROM lineitem WHERE l_quantity IN (1, 7, 49) AND l_discount BETWEEN 0.02 AND 0.05 AND l_shipdate IS NOT NULL")
def predicates_lineitem(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_shipdate")
    return rows.where(F.col("l_quantity").isin(1.0, 7.0, 49.0) & F.col("l_discount").between(0.02, 0.05) & F.col("l_shipdate").isNotNull()).select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"))


@query("SELECT quality::BIGINT AS quality, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents JOIN labels USING (doc_id) GROUP BY quality")
def labels_slice(spark: SparkSession, d: str) -> DataFrame:
    docs, labels = read_table(spark, d, "documents", "doc_id", "n_chars"), read_table(spark, d, "labels", "doc_id", "quality")
    return docs.join(labels, "doc_id").groupBy(F.col("quality").cast("long").alias("quality")).agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query(f"SELECT r_name, sum(val) AS total FROM ({WORKLOADS['w09'].sql}) JOIN nation ON c1 = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def rollup_regions(spark: SparkSession, d: str) -> DataFrame:
    nation, region = read_table(spark, d, "nation", "n_nationkey", "n_regionkey"), read_table(spark, d, "region", "r_regionkey", "r_name")
    rows = WORKLOADS["w09"].build(spark, d).join(nation, F.col("c1") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.groupBy("r_name").agg(F.sum("val").alias("total"))


def sampled_reuse(df: DataFrame, mode: int, share: float, seed: int = 1) -> DataFrame:
    """Average reuse of a mode estimated from a sample of its output rows: rows are drawn whole, by a hash of their index."""
    key = F.col(f"c{mode + 1}")
    drawn = df.where(F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1_000_000)) < int(share * 1_000_000))
    return drawn.agg((F.count(F.lit(1)) / F.approx_count_distinct(key)).alias("reuse"))


@query()
def sampled_reuse_w01(spark: SparkSession, d: str) -> DataFrame:
    return sampled_reuse(WORKLOADS["w01"].build(spark, d), 0, 0.5)


def _scalars(columns: dict[str, tuple[Callable[[], Column], str]], table: str, key: str) -> tuple[Callable, str]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return spark.read.parquet(f"{d}/{table}.parquet").select(key, *[c().alias(n) for n, (c, _) in columns.items()])

    return run, f"SELECT {key}, {', '.join(f'{s} AS {n}' for n, (_, s) in columns.items())} FROM {table}"


def _scalar_families() -> dict[str, tuple[Callable, str]]:
    c = F.col
    long = lambda x: x.cast("long")
    return {
        "scalar_strings": _scalars({"low": (lambda: F.lower("url"), "lower(url)"), "head": (lambda: F.substring("url", 1, 12), "substr(url, 1, 12)"), "size": (lambda: long(F.length("html")), "length(html)::BIGINT"), "host": (lambda: F.regexp_extract("url", r"https?://([^/:]+)", 1), "regexp_extract(url, 'https?://([^/:]+)', 1)"), "parts": (lambda: long(F.size(F.split("url", "/"))), "len(string_split(url, '/'))::BIGINT")}, "pages", "page_id"),
        "scalar_dates": _scalars({"y": (lambda: long(F.year("ts")), "year(ts)"), "m": (lambda: long(F.month("ts")), "month(ts)"), "h": (lambda: long(F.hour("ts")), "hour(ts)"), "day": (lambda: long(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))), "date_diff('day', DATE '2024-01-01', ts::DATE)"), "us": (lambda: F.unix_micros(c("ts").cast("timestamp")), "epoch_us(ts)"), "hour_start": (lambda: F.unix_micros(F.date_trunc("hour", "ts").cast("timestamp")), "epoch_us(date_trunc('hour', ts))")}, "events", "event_id"),
        "scalar_math": _scalars({"up": (lambda: long(F.ceil(c("o_totalprice"))), "ceil(o_totalprice)::BIGINT"), "down": (lambda: long(F.floor(c("o_totalprice"))), "floor(o_totalprice)::BIGINT"), "size": (lambda: F.abs(c("o_totalprice") - 1000), "abs(o_totalprice - 1000)"), "root": (lambda: F.sqrt("o_totalprice"), "sqrt(o_totalprice)"), "most": (lambda: F.greatest("o_orderkey", "o_custkey"), "greatest(o_orderkey, o_custkey)"), "least_key": (lambda: F.least("o_orderkey", "o_custkey"), "least(o_orderkey, o_custkey)"), "levels": (lambda: long(F.ceil(F.log2(c("o_orderkey") + 2))), "ceil(log2(o_orderkey + 2))::BIGINT")}, "orders", "o_orderkey"),
        "scalar_bits": _scalars({"up": (lambda: F.shiftleft("o_custkey", 3), "o_custkey << 3"), "down": (lambda: F.shiftright("o_custkey", 2), "o_custkey >> 2"), "both": (lambda: c("o_custkey").bitwiseAND(c("o_orderkey")), "o_custkey & o_orderkey"), "any_bit": (lambda: c("o_custkey").bitwiseOR(c("o_orderkey")), "o_custkey | o_orderkey"), "odd": (lambda: c("o_custkey").bitwiseXOR(c("o_orderkey")), "xor(o_custkey, o_orderkey)"), "ones": (lambda: long(F.bit_count("o_custkey")), "bit_count(o_custkey)::BIGINT"), "third": (lambda: long(F.getbit("o_custkey", F.lit(2))), "(o_custkey >> 2) & 1")}, "orders", "o_orderkey"),
        "scalar_arrays": _scalars({"first": (lambda: c("embedding")[0].cast("double"), "embedding[1]::DOUBLE"), "most": (lambda: F.array_max("embedding").cast("double"), "list_max(embedding)::DOUBLE"), "n": (lambda: long(F.size("embedding")), "len(embedding)::BIGINT"), "positive": (lambda: long(F.size(F.filter("embedding", lambda x: x > 0))), "len(list_filter(embedding, lambda x: x > 0))::BIGINT"), "doubled": (lambda: F.transform("embedding", lambda x: x.cast("double") * 2)[5], "embedding[6]::DOUBLE * 2"), "third": (lambda: F.element_at("embedding", 3).cast("double"), "embedding[3]::DOUBLE")}, "embeddings", "vec_id"),
        "scalar_json": _scalars({"k": (lambda: long(F.get_json_object("props", "$.k")), "json_extract_string(props, '$.k')::BIGINT"), "from": (lambda: long(F.from_json("props", "k long")["k"]), "json_extract_string(props, '$.k')::BIGINT"), "made": (lambda: F.to_json(F.struct(F.col("event_id").alias("e"))), "'{\"e\":' || event_id || '}'"), "mapped": (lambda: F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array("event_id", "user_id"))["b"], "user_id")}, "events", "event_id"),
    }


for _family, (_query, _sql) in _scalar_families().items():
    QUERIES[_family], ORACLES[_family] = _query, _sql.replace(" AS from,", ' AS "from",')

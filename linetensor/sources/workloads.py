"""The workload tensors W1 to W12 on the given tables: coordinates c1..cN and a value.

Each has its Spark builder and the same definition in DuckDB SQL. Equal coordinates are summed and
zeros dropped. String modes are numbered by rank in byte order.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .tables import read_table

#: A dictionary of up to so many keys is broadcast; beyond, it is joined by its key.
SMALL_DICTIONARY = 1 << 16


def dictionary(df: DataFrame, column: str, buckets: int = 256) -> DataFrame:
    """(key, idx): distinct non-null values numbered from 0 in byte order.

    Keys are dealt into ranges by their first two bytes, ranked inside each range, and shifted by
    the number of keys in the ranges before: no single task sees all keys.
    """
    keys = df.select(F.col(column).alias("key")).where("key IS NOT NULL").distinct()
    keys = keys.withColumn("range", F.coalesce(F.conv(F.substring(F.rpad(F.hex(F.encode("key", "UTF-8")), 4, "0"), 1, 4), 16, 10).cast("int"), F.lit(0)))
    sizes = sorted((r["range"], r["n"]) for r in keys.groupBy("range").agg(F.count(F.lit(1)).alias("n")).collect())  # at most 65,536 rows
    before, rows = 0, []
    for at, n in sizes:
        rows.append((at, before))
        before += n
    shifts = df.sparkSession.createDataFrame(rows, "range int, before long")
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("range").orderBy(F.encode("key", "UTF-8"))) - 1
    return keys.join(F.broadcast(shifts), "range").select("key", (F.col("before") + rank).cast("long").alias("idx"))


def numbered(df: DataFrame, column: str, name: str, how: str = "inner") -> DataFrame:
    """df with the rank of a string column as a BIGINT column; rows without the string are left out, unless the join is a left one."""
    ranks = dictionary(df, column).select(F.col("key").alias(f"__{name}_key"), F.col("idx").alias(name))
    if ranks.limit(SMALL_DICTIONARY + 1).count() <= SMALL_DICTIONARY:
        ranks = F.broadcast(ranks)
    return df.join(ranks, F.col(column) == F.col(f"__{name}_key"), how).drop(f"__{name}_key")


def coo(df: DataFrame, coords: list[Column], value: Column) -> DataFrame:
    """Distinct coordinates with summed values; rows without a coordinate or value are left out, and so are zeros."""
    named = [c.cast("long").alias(f"c{i + 1}") for i, c in enumerate(coords)]
    rows = df.select(*named, value.cast("double").alias("val")).dropna()
    keys = [f"c{i + 1}" for i in range(len(coords))]
    # the cast away from nullable types lets encoders skip null checks
    out = rows.groupBy(*keys).agg(F.sum("val").alias("val")).where("val <> 0")
    return out.select(*[F.coalesce(k, F.lit(0).cast("long")).alias(k) for k in keys], F.coalesce("val", F.lit(0.0)).alias("val"))


def _months(column: str) -> Column:
    return (F.year(column) - 1995) * 12 + F.month(column) - 1


def _days(column: str, origin: str) -> Column:
    return F.datediff(F.to_date(column), F.lit(origin).cast("date"))


def _w1(spark: SparkSession, d: str, most: int | None = None) -> DataFrame:
    rows = read_table(spark, d, "lineitem", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity")
    rows = rows.where(F.col("l_quantity") <= most) if most else rows
    return coo(rows, [F.col("l_partkey"), F.col("l_suppkey"), _months("l_shipdate")], F.col("l_quantity"))


def _w2(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_quantity")
    return coo(rows, [F.col("l_orderkey"), F.col("l_partkey"), F.col("l_linenumber") - 1], F.col("l_quantity"))


def _w4(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "orders", "o_custkey", "o_orderdate", "o_orderpriority", "o_orderstatus").where("o_orderstatus <> 'P'")
    return coo(numbered(rows, "o_orderpriority", "priority"), [F.col("o_custkey"), _months("o_orderdate"), F.col("priority")], F.lit(1.0))


def _events(spark: SparkSession, d: str, *columns: str) -> DataFrame:
    return numbered(read_table(spark, d, "events", "user_id", "event_type", "ts", *columns), "event_type", "type")


def _event_k() -> Column:
    return F.get_json_object("props", "$.k").cast("long")


def _w5(spark: SparkSession, d: str) -> DataFrame:
    return coo(_events(spark, d), [F.col("user_id"), F.col("type"), _days("ts", "2024-01-01"), F.hour("ts")], F.lit(1.0))


def _w6(spark: SparkSession, d: str) -> DataFrame:
    docs = numbered(read_table(spark, d, "documents", "doc_id", "text", "source"), "source", "src")
    words = docs.select("doc_id", "src", F.explode(F.split("text", "[ \n]+")).alias("token")).where("token <> ''")
    words = words.groupBy("doc_id", "src", "token").agg(F.count(F.lit(1)).alias("n"))
    return coo(numbered(words, "token", "tok"), [F.col("doc_id"), F.col("tok"), F.col("src")], F.col("n"))


def w6_texts(spark: SparkSession, d: str) -> DataFrame:
    """The documents of W6 before their words are split: c1, c3 and text; c3 is null where there is no source."""
    docs = numbered(read_table(spark, d, "documents", "doc_id", "text", "source"), "source", "src", "left")
    return docs.select(F.col("doc_id").cast("long").alias("c1"), F.col("src").alias("c3"), "text")


def _w7(spark: SparkSession, d: str) -> DataFrame:
    micros = F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(1704067200000000)
    return coo(_events(spark, d, "event_id", "value", "props"), [F.col("event_id"), F.col("user_id"), F.col("type"), micros, _event_k()], F.round(F.col("value") * 100))


def _w8(spark: SparkSession, d: str) -> DataFrame:
    items = read_table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_shipdate", "l_returnflag", "l_quantity")
    orders = read_table(spark, d, "orders", "o_orderkey", "o_custkey")
    rows = numbered(items, "l_returnflag", "flag").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return coo(rows, [F.col("o_custkey"), F.col("l_partkey"), F.col("l_suppkey"), _days("l_shipdate", "1995-01-01"), F.col("flag")], F.col("l_quantity"))


def _w9(spark: SparkSession, d: str) -> DataFrame:
    items = read_table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_shipdate", "l_quantity")
    orders = read_table(spark, d, "orders", "o_orderkey", "o_custkey")
    customers = read_table(spark, d, "customer", "c_custkey", "c_nationkey")
    parts = numbered(numbered(read_table(spark, d, "part", "p_partkey", "p_brand", "p_type"), "p_brand", "brand"), "p_type", "kind")
    buyers = orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")
    rows = items.join(buyers, F.col("l_orderkey") == F.col("o_orderkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return coo(rows, [F.col("c_nationkey"), F.col("brand"), F.col("kind"), F.year("l_shipdate") - 1995], F.col("l_quantity"))


def _w10(spark: SparkSession, d: str) -> DataFrame:
    return coo(_events(spark, d, "props"), [F.col("user_id"), F.col("type"), _days("ts", "2024-01-01"), F.hour("ts"), _event_k()], F.lit(1.0))


def _w11(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("at", "x"))
    return coo(rows, [F.col("vec_id"), F.col("at")], F.round(F.col("x").cast("double") * (1 << 20)))


def _w12(spark: SparkSession, d: str) -> DataFrame:
    return coo(numbered(read_table(spark, d, "conversations", "conv_id", "turn", "role"), "role", "r"), [F.col("conv_id"), F.col("turn"), F.col("r")], F.lit(1.0))


def _small(spark: SparkSession, d: str) -> DataFrame:
    rows = numbered(read_table(spark, d, "lineitem", "l_shipdate", "l_linenumber", "l_linestatus", "l_quantity"), "l_linestatus", "status")
    return coo(rows, [F.quarter("l_shipdate") - 1, F.col("l_linenumber"), F.col("status")], F.col("l_quantity"))


_MONTH_SQL = "(year({c}) - 1995) * 12 + month({c}) - 1"
_SHIP_MONTH, _ORDER_MONTH = _MONTH_SQL.format(c="l_shipdate"), _MONTH_SQL.format(c="o_orderdate")


def _rank_sql(column: str, source: str) -> str:
    return f"(SELECT {column} AS key, row_number() OVER (ORDER BY {column}) - 1 AS idx FROM (SELECT DISTINCT {column} FROM {source}))"


def _sum_sql(coords: list[str], value: str, source: str) -> str:
    named = ", ".join(f"({c})::BIGINT AS c{i + 1}" for i, c in enumerate(coords))
    keys = ", ".join(f"c{i + 1}" for i in range(len(coords)))
    return f"SELECT {keys}, sum(val) AS val FROM (SELECT {named}, ({value})::DOUBLE AS val FROM {source}) GROUP BY {keys} HAVING sum(val) <> 0"


_EVENT_SQL = f"events JOIN {_rank_sql('event_type', 'events')} t ON event_type = t.key"
_K_SQL = "json_extract_string(props, '$.k')::BIGINT"
_DAY_SQL = "date_diff('day', DATE '2024-01-01', ts::DATE)"


@dataclass(frozen=True)
class Workload:
    """A workload tensor: its modes' names, its builder and its SQL."""

    name: str
    modes: tuple[str, ...]
    build: Callable[[SparkSession, str], DataFrame]
    sql: str

    @property
    def order(self) -> int:
        return len(self.modes)

    @property
    def denominator(self) -> int:
        """Of the deterministic factors: small enough that all sums of products are exact in doubles."""
        return 64 if self.order <= 4 else 16


_TOKENS = r"(SELECT doc_id, source, unnest(regexp_split_to_array(text, '[ \n]+')) AS token FROM documents)"
_LO = "lineitem JOIN orders ON l_orderkey = o_orderkey"

WORKLOADS = {
    w.name: w
    for w in [
        Workload("w01", ("part", "supplier", "month"), _w1, _sum_sql(["l_partkey", "l_suppkey", _SHIP_MONTH], "l_quantity", "lineitem")),
        Workload("w02", ("order", "part", "line"), _w2, _sum_sql(["l_orderkey", "l_partkey", "l_linenumber - 1"], "l_quantity", "lineitem")),
        Workload("w03", ("part", "supplier", "month"), lambda s, d: _w1(s, d, 10), _sum_sql(["l_partkey", "l_suppkey", _SHIP_MONTH], "l_quantity", "lineitem WHERE l_quantity <= 10")),
        Workload("w04", ("customer", "month", "priority"), _w4, _sum_sql(["o_custkey", _ORDER_MONTH, "t.idx"], "1", f"(SELECT * FROM orders WHERE o_orderstatus <> 'P') o JOIN {_rank_sql('o_orderpriority', chr(40) + 'SELECT * FROM orders WHERE o_orderstatus <> ' + chr(39) + 'P' + chr(39) + chr(41))} t ON o_orderpriority = t.key")),
        Workload("w05", ("user", "type", "day", "hour"), _w5, _sum_sql(["user_id", "t.idx", _DAY_SQL, "hour(ts)"], "1", _EVENT_SQL)),
        Workload("w06", ("document", "token", "source"), _w6, _sum_sql(["doc_id", "t.idx", "s.idx"], "1", f"(SELECT * FROM {_TOKENS} WHERE token <> '') k JOIN {_rank_sql('token', '(SELECT token FROM ' + _TOKENS + chr(32) + 'WHERE token <> ' + chr(39) * 2 + ')')} t ON k.token = t.key JOIN {_rank_sql('source', 'documents')} s ON k.source = s.key")),
        Workload("w07", ("event", "user", "type", "micros", "k"), _w7, _sum_sql(["event_id", "user_id", "t.idx", "epoch_us(ts) - 1704067200000000", _K_SQL], "round(value * 100)", _EVENT_SQL)),
        Workload("w08", ("customer", "part", "supplier", "day", "flag"), _w8, _sum_sql(["o_custkey", "l_partkey", "l_suppkey", "date_diff('day', DATE '1995-01-01', l_shipdate::DATE)", "t.idx"], "l_quantity", f"{_LO} JOIN {_rank_sql('l_returnflag', 'lineitem')} t ON l_returnflag = t.key")),
        Workload("w09", ("nation", "brand", "type", "year"), _w9, _sum_sql(["c_nationkey", "b.idx", "t.idx", "year(l_shipdate) - 1995"], "l_quantity", f"{_LO} JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN {_rank_sql('p_brand', 'part')} b ON p_brand = b.key JOIN {_rank_sql('p_type', 'part')} t ON p_type = t.key")),
        Workload("w10", ("user", "type", "day", "hour", "k"), _w10, _sum_sql(["user_id", "t.idx", _DAY_SQL, "hour(ts)", _K_SQL], "1", _EVENT_SQL)),
        Workload("w11", ("vector", "dimension"), _w11, _sum_sql(["vec_id", "n - 1"], "round(x::DOUBLE * 1048576)", "(SELECT vec_id, unnest(embedding) AS x, unnest(range(1, len(embedding) + 1)) AS n FROM embeddings)")),
        Workload("w12", ("conversation", "turn", "role"), _w12, _sum_sql(["conv_id", "turn", "t.idx"], "1", f"conversations JOIN {_rank_sql('role', 'conversations')} t ON role = t.key")),
    ]
}

#: The worked example of a plan, 4 x 8 x 2 in the given tables: quarters, lines of an order and their status.
SMALL = Workload("small", ("quarter", "line", "status"), _small, _sum_sql(["quarter(l_shipdate) - 1", "l_linenumber", "t.idx"], "l_quantity", f"lineitem JOIN {_rank_sql('l_linestatus', 'lineitem')} t ON l_linestatus = t.key"))

COO_TYPES = {n: T.StructType([*[T.StructField(f"c{i + 1}", T.LongType()) for i in range(n)], T.StructField("val", T.DoubleType())]) for n in range(1, 7)}

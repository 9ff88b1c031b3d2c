"""Inputs of the experiments on the given tables: (seq, v) in arrival order, and the same in DuckDB's SQL.

Derived inputs map a hash-made u in (0, 1) by functions that rise with u, so their exact ranks are those of an order
key `o` that both engines compute to the last bit, whatever the last bit of a logarithm.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import pi

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from rankfit.sources.io import table

TWO52 = 4503599627370496.0


def unit(key: Column) -> Column:
    """u in (0, 1) from 13 hex digits of a key's MD5."""
    return (F.conv(F.substring(F.md5(key.cast("string")), 1, 13), 16, 10).cast("double") + 0.5) / TWO52


def sign(key: Column) -> Column:
    return F.when(F.conv(F.substring(F.md5(key.cast("string")), 14, 1), 16, 10).cast("int") < 8, -1.0).otherwise(1.0)


U_SQL = "((CAST(('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 13)) AS BIGINT) + 0.5) / 4503599627370496.0)"
S_SQL = "(CASE WHEN CAST(('0x' || substr(md5(CAST(event_id AS VARCHAR)), 14, 1)) AS INT) < 8 THEN -1.0 ELSE 1.0 END)"
BELL_SQL = "SELECT CAST(unnest(embedding) AS DOUBLE) AS o FROM embeddings"


def normal_of(u: Column) -> Column:
    """Inverse of the normal CDF, by its logistic-like approximation: monotone, which is what ranks need."""
    return F.signum(u - 0.5) * F.sqrt(-F.lit(pi / 2) * F.log(1 - F.pow(2 * u - 1, F.lit(2.0))))


@dataclass(frozen=True)
class Workload:
    name: str
    rows: Callable[[SparkSession, str], DataFrame]  # (seq, v)
    order_sql: str  # column o
    eps: float  # allowed rank error at k = 100, as a share of n
    native: bool = False  # v itself is exact in both engines
    one_stream: bool = False  # arrival order across the whole input matters
    axis: str = "f64"


def _events(value: Callable[[Column, Column], Column]):
    def rows(spark: SparkSession, folder: str) -> DataFrame:
        key = F.col("event_id")
        return table(spark, folder, "events").select(key.alias("seq"), value(unit(key), sign(key)).alias("v"))

    return rows


def bell(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "x"))
    return rows.select((F.col("vec_id") * 4096 + F.col("pos")).alias("seq"), F.col("x").cast("double").alias("v"))


def _column(name: str, seq: str, column: str):
    return lambda spark, folder: table(spark, folder, name).select(F.expr(seq).cast("long").alias("seq"), F.expr(column).alias("v"))


def _after(spark: SparkSession, folder: str, second: Column | None, other: DataFrame | None = None) -> DataFrame:
    first = bell(spark, folder)
    then = first.withColumn("v", second) if other is None else other
    return first.unionByName(then.withColumn("seq", F.col("seq") + F.lit(1 << 50)))


def _mix(spark: SparkSession, folder: str) -> DataFrame:
    heavy = table(spark, folder, "lineitem").where("l_quantity <= 42").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("seq"), F.col("l_quantity").alias("v"))
    return _after(spark, folder, None, heavy)


def _frequent(spark: SparkSession, folder: str) -> DataFrame:
    times = (F.conv(F.substring(F.md5(F.col("p_partkey").cast("string")), 1, 6), 16, 10).cast("long") % 60) + 1
    return table(spark, folder, "part").select((F.col("p_partkey") * 64).alias("base"), F.col("p_partkey").cast("double").alias("v"), F.explode(F.sequence(F.lit(1).cast("long"), times)).alias("i")).select((F.col("base") + F.col("i")).alias("seq"), "v")


_FREQUENT_SQL = "SELECT CAST(p_partkey AS DOUBLE) AS o FROM (SELECT p_partkey, unnest(range(0, CAST(('0x' || substr(md5(CAST(p_partkey AS VARCHAR)), 1, 6)) AS BIGINT) % 60 + 1)) AS i FROM part)"
_U = f"SELECT {U_SQL} AS o FROM events"
_SU = f"SELECT {S_SQL} * {U_SQL} AS o FROM events"

WORKLOADS = {
    w.name: w
    for w in (
        Workload("bell", bell, BELL_SQL, 0.002, True),
        Workload("power_like", _column("events", "event_id", "value"), "SELECT value AS o FROM events", 0.004, True),
        Workload("ticks", _column("events", "event_id", "unix_micros(cast(ts as timestamp))"), "SELECT CAST(epoch_us(ts) AS DOUBLE) AS o FROM events", 0.004, axis="i64"),
        Workload("wide_keys", _column("events", "event_id", "cast(conv(substring(md5(cast(event_id as string)), 1, 15), 16, 10) as bigint)"), "SELECT CAST(('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 15)) AS BIGINT) AS o FROM events", 0.004, axis="i64"),
        Workload("uniform", _column("lineitem", "l_orderkey * 8 + l_linenumber", "l_extendedprice"), "SELECT l_extendedprice AS o FROM lineitem", 0.002, True),
        Workload("normal", _events(lambda u, s: normal_of(u)), _U, 0.003),
        Workload("pareto", _events(lambda u, s: F.pow(1 - u, F.lit(-1 / 1.5))), _U, 0.004),
        Workload("gumbel", _events(lambda u, s: -F.log(-F.log(u))), _U, 0.003),
        Workload("lognormal", _events(lambda u, s: F.exp(normal_of(u))), _U, 0.004),
        Workload("loguniform", _events(lambda u, s: F.pow(F.lit(10.0), u * 6 - 3)), _U, 0.004),
        Workload("signed", _events(lambda u, s: s * F.pow(F.lit(10.0), u * 6 - 3)), _SU, 0.006),
        Workload("signed_wide", _events(lambda u, s: s * F.pow(F.lit(10.0), u * 300 - 150)), _SU, 0.04),
        Workload("shift_small", lambda s, d: _after(s, d, F.col("v") * 1.2 + 0.05), f"SELECT o FROM ({BELL_SQL}) UNION ALL SELECT o * 1.2 + 0.05 FROM ({BELL_SQL})", 0.003, True, True),
        Workload("shift_large", lambda s, d: _after(s, d, F.col("v") * 100 + 10), f"SELECT o FROM ({BELL_SQL}) UNION ALL SELECT o * 100.0 + 10.0 FROM ({BELL_SQL})", 0.006, True, True),
        Workload("mix_heavy", _mix, f"SELECT o FROM ({BELL_SQL}) UNION ALL SELECT l_quantity FROM lineitem WHERE l_quantity <= 42", 0.002, True, True),
        Workload("sorted_frequent", _frequent, _FREQUENT_SQL, 0.005, True, True),
        Workload("chars", _column("documents", "doc_id", "cast(n_chars as double)"), "SELECT CAST(n_chars AS DOUBLE) AS o FROM documents", 0.008, True),
        Workload("html", _column("pages", "page_id", "cast(length(html) as double)"), "SELECT CAST(length(html) AS DOUBLE) AS o FROM pages", 0.01, True),
        Workload("turns", _column("conversations", "conv_id * 1000 + turn", "cast(length(text) as double)"), "SELECT CAST(length(text) AS DOUBLE) AS o FROM conversations", 0.01, True),
        Workload("quantity", _column("lineitem", "l_orderkey * 8 + l_linenumber", "l_quantity"), "SELECT l_quantity AS o FROM lineitem", 0.0, True),
        Workload("balance", _column("customer", "c_custkey", "c_acctbal"), "SELECT c_acctbal AS o FROM customer", 0.006, True),
        Workload("total", _column("orders", "o_orderkey", "o_totalprice"), "SELECT o_totalprice AS o FROM orders", 0.003, True),
    )
}


def get(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return WORKLOADS[name].rows


def chunked(df: DataFrame, chunks: int) -> DataFrame:
    """`df` with `chunk`: equal shares of the arrival order, without a sort of the whole input in one task."""
    from rankfit.plans.exact import numbered

    return numbered(df, "seq").withColumn("chunk", F.floor((F.col("number") - 1) * chunks / F.col("total")).cast("int")).drop("number", "total")

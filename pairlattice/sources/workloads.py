"""Workloads on the given tables: attribute lists in Spark and in DuckDB SQL, generated sets, small examples."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.functions.shingles import shingle_set, super_shingles, super_shingles_sql


@dataclass(frozen=True)
class Workload:
    """``rid`` and attributes as expressions; DuckDB's where it differs."""

    name: str
    table: str
    rid: str
    attrs: tuple[str, ...]
    duck: tuple[str, ...] = ()
    duck_rid: str = ""
    join: str = ""
    where: str = ""

    @property
    def d(self) -> int:
        return len(self.attrs)

    @property
    def cols(self) -> list[str]:
        return [f"a{i + 1}" for i in range(self.d)]

    def frame(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        df = spark.read.parquet(f"{sf_dir}/{self.table}.parquet")
        if self.join:
            other, key = self.join.split(":")
            left, right = key.split("=")
            df = df.join(spark.read.parquet(f"{sf_dir}/{other}.parquet"), F.col(left) == F.col(right))
        if self.where:
            df = df.where(self.where)
        return df.selectExpr(f"{self.rid} AS rid", *[f"{e} AS a{i + 1}" for i, e in enumerate(self.attrs)])

    def sql(self) -> str:
        cols = ", ".join(f"{e} AS a{i + 1}" for i, e in enumerate(self.duck or self.attrs))
        source = self.table
        if self.join:
            other, key = self.join.split(":")
            source += f" JOIN {other} ON {key}"
        return f"SELECT {self.duck_rid or self.rid} AS rid, {cols} FROM {source}" + (f" WHERE {self.where}" if self.where else "")


ORDERS = ("o_custkey", "o_orderstatus", "o_orderpriority", "year(o_orderdate)", "month(o_orderdate)")
LINE_ID = "xxhash64(l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate)"
LINE_DUCK = "hash(l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate)"
URL = tuple(
    f"regexp_extract(url, '^(?:([^:/?#]+):)?(?://([^/?#]*))?(?:/([^/?#]*))?([^?#]*)(?:[?]([^#]*))?(?:#(.*))?$', {i})" for i in range(1, 7)
)
EVENTS = ("user_id", "to_date(ts)", "event_type", "cast(floor(value / 10) as bigint)", "get_json_object(props, '$.k')")
EVENTS_DUCK = ("user_id", "CAST(ts AS DATE)", "event_type", "CAST(floor(value / 10) AS BIGINT)", "json_extract_string(props, '$.k')")

TABLES = {
    w.name: w
    for w in (
        Workload("orders5", "orders", "o_orderkey", ORDERS),
        Workload("orders6", "orders", "o_orderkey", (*ORDERS, "day(o_orderdate)")),
        Workload("lineitem_mixed6", "lineitem", LINE_ID, ("cast(l_quantity as int)", "cast(round(l_discount * 100) as int)", "cast(round(l_tax * 100) as int)", "l_returnflag", "l_linestatus", "l_linenumber"), duck_rid=LINE_DUCK),
        Workload("lineitem_biblio5", "lineitem", LINE_ID, ("l_partkey", "l_suppkey", "cast(l_shipdate as date)", "cast(l_quantity as bigint)", "l_returnflag"), duck_rid=LINE_DUCK),
        Workload("part5", "part", "p_partkey", ("p_name", "p_brand", "p_type", "p_size", "cast(round(p_retailprice * 100) as bigint)")),
        Workload("events5", "events", "event_id", EVENTS, EVENTS_DUCK),
        Workload("embed8", "embeddings", "vec_id", tuple(f"embedding[{i}] >= 0" for i in range(8)), tuple(f"embedding[{i + 1}] >= 0" for i in range(8))),
        Workload("customer3", "customer", "c_custkey", ("c_nationkey", "c_mktsegment", "cast(floor(c_acctbal / 1000) as bigint)")),
        Workload("jointree5", "orders", "o_orderkey", ("c_nationkey", "c_mktsegment", "o_orderstatus", "o_orderpriority", "year(o_orderdate)"), join="customer:o_custkey=c_custkey"),
        Workload("page_url6", "pages", "page_id", URL),
        Workload("nulls3", "orders", "o_orderkey", ("nullif(o_custkey % 7, 0)", "nullif(o_orderstatus, 'P')", "o_orderpriority")),
    )
}


def shingle_frame(spark: SparkSession, sf_dir: str, table: str = "documents", rid: str = "doc_id", features: int = 6, q: int = 1, m: int = 1, oracle: bool = True) -> DataFrame:
    """(rid, a1..): super-shingle vectors of a table's texts."""
    return shingled(spark.read.parquet(f"{sf_dir}/{table}.parquet").selectExpr(f"{rid} AS rid", "text"), features, q, m, oracle)


def shingled(df: DataFrame, features: int = 6, q: int = 1, m: int = 1, oracle: bool = True) -> DataFrame:
    """(rid, a1..) from (rid, text), of a table or a stream."""
    df = df.withColumn("_s", shingle_set(F.col("text"), q))
    return df.select("rid", *[c.alias(f"a{i + 1}") for i, c in enumerate(super_shingles(F.col("_s"), features, m, oracle))])


def shingle_sql(table: str = "documents", rid: str = "doc_id", features: int = 6) -> str:
    return f"SELECT {rid} AS rid, {super_shingles_sql('text', features)} FROM {table}"


def generated_pairs(spark: SparkSession, sf_dir: str, unique_share: float, group: int) -> DataFrame:
    """(rid, a1..a5): a share of unique records; the others in groups that agree on all fields but one, fixed per group.

    Records stand for the rows of lineitem: row numbers below the table's size, so only its count is read.
    """
    n = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count()
    cut = int(unique_share * n)
    end = cut + (n - cut) // group * group
    i, grp = F.col("id"), F.floor((F.col("id") - cut) / group)
    own = F.col("id") + F.lit(10_000_000_000)
    cols = [F.when((i < cut) | (grp % 5 == f), own).otherwise(grp).cast("long").alias(f"a{f + 1}") for f in range(5)]
    return spark.range(0, end).select(i.alias("rid"), *cols)


def generated_sql(unique_share: str, group: int) -> str:
    cut = f"CAST(floor({unique_share} * n) AS BIGINT)"
    cols = ", ".join(f"CASE WHEN i < cut OR ((i - cut) // {group}) % 5 = {f} THEN i + 10000000000 ELSE (i - cut) // {group} END AS a{f + 1}" for f in range(5))
    return f"SELECT i AS rid, {cols} FROM (SELECT unnest(range(0, cut + (n - cut) // {group} * {group})) AS i, cut FROM (SELECT n, {cut} AS cut FROM (SELECT count(*) AS n FROM lineitem)))"


#: Name -> (share of unique records, members of a group).
GENERATED = {"pairs_40_60": (0.4, 2), "pairs_20_80": (0.2, 16), "pairs_10_90": (0.1, 81)}


def duplicated(df: DataFrame, times: int) -> DataFrame:
    """Every record ``times`` times, each copy with an identity of its own."""
    return df.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(times)))).withColumn("rid", F.xxhash64("rid", "copy")).drop("copy")


def example_relation(spark: SparkSession) -> DataFrame:
    """Four records of three fields: two pairs agree on two of them."""
    return spark.createDataFrame([(1, "a1", "b1", "c1"), (2, "a2", "b2", "c2"), (3, "a1", "b1", "c3"), (4, "a3", "b2", "c2")], "rid long, a1 string, a2 string, a3 string")


def counterexamples(spark: SparkSession) -> list[tuple[DataFrame, DataFrame, int, int]]:
    """(A, B, threshold, join size) where the join exceeds half the sum of the self-joins."""
    one = "rid long, a1 string, a2 string, a3 string"
    a = spark.createDataFrame([(1, "x", "y", "z")], one)
    b = spark.createDataFrame([(1, "x", "y", "p"), (2, "x", "q", "z")], one)
    c = spark.createDataFrame([(1, "x", "y", "p"), (2, "x", "q", "z"), (3, "o", "y", "z")], one)
    return [(a, b, 2, 2), (a, c, 2, 3)]

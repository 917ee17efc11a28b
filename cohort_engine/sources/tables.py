"""Activity tables: readers, the canonical tables over the test data, replication, and the catalog."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import ActivitySchema, ActivityTable, CohortSemanticError

EVENTS = ActivitySchema("user_id", "ts", "action", ("role", "country", "city", "zone"), ("gold", "k"), ("event_id",))


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_csv(spark: SparkSession, path: str, schema: ActivitySchema, types: T.StructType, header: bool = True, name: str = "log") -> ActivityTable:
    """A raw activity log; the types are given, never inferred, and a wrong column stops the read."""
    missing = set(schema.columns) - set(types.names)
    if missing:
        raise CohortSemanticError(f"the log's types lack {sorted(missing)}")
    return ActivityTable(spark.read.csv(path, schema=types, header=header, mode="FAILFAST", enforceSchema=False), schema, name)


def read_parquet(spark: SparkSession, path: str, schema: ActivitySchema, name: str = "activities") -> ActivityTable:
    df = spark.read.parquet(path)
    missing = set(schema.columns) - set(df.columns)
    if missing:
        raise CohortSemanticError(f"{path} lacks {sorted(missing)}")
    return ActivityTable(df, schema, name)


def _homes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with the name of their nation. Left to Spark to broadcast: it does so where sizes allow."""
    c, n = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    return c.join(n, c.c_nationkey == n.n_nationkey).select(F.col("c_custkey").alias("_c"), F.col("n_name").alias("country"), F.col("c_mktsegment").alias("city"))


def activity_events(spark: SparkSession, sf_dir: str) -> ActivityTable:
    e = load(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k").cast("int"))
    joined = e.join(_homes(spark, sf_dir), F.col("user_id") == F.col("_c"))
    df = joined.select(
        "user_id", "ts", F.col("event_type").alias("action"), F.col("value").alias("gold"), "k",
        F.concat(F.lit("r"), F.col("k") % 4).alias("role"), "country", "city", F.expr("concat('z', k div 20)").alias("zone"), "event_id",
    )
    return ActivityTable(df, EVENTS, "events")


def activity_launch(spark: SparkSession, sf_dir: str, staggered: bool = False) -> ActivityTable:
    """Events whose first tuple of each user is a launch; ``staggered`` shifts each user's times by up to 19 days."""
    act = activity_events(spark, sf_dir)
    first = act.df.groupBy(F.col("user_id").alias("_u")).agg(F.min(F.struct("ts", "event_id")).alias("_f"))
    df = act.df.join(first, F.col("user_id") == F.col("_u"))
    df = df.withColumn("action", F.when(F.struct("ts", "event_id") == F.col("_f"), "launch").otherwise(F.col("action")))
    if staggered:
        df = df.withColumn("ts", F.expr("ts + make_dt_interval(cast(pmod(user_id * 7, 20) as int))"))
    return ActivityTable(df.select(*act.df.columns), EVENTS, "launch")


def activity_orders(spark: SparkSession, sf_dir: str) -> ActivityTable:
    o = load(spark, sf_dir, "orders").join(_homes(spark, sf_dir), F.col("o_custkey") == F.col("_c"))
    schema = ActivitySchema("o_custkey", "o_orderdate", "o_orderstatus", ("o_orderpriority", "country", "city"), ("o_totalprice",), ("o_orderkey",))
    return ActivityTable(o.select(*schema.columns), schema, "orders")


def activity_lineitem(spark: SparkSession, sf_dir: str) -> ActivityTable:
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = load(spark, sf_dir, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(_homes(spark, sf_dir), F.col("o_custkey") == F.col("_c"))
    tie = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    schema = ActivitySchema("o_custkey", "l_shipdate", "l_returnflag", ("l_linestatus", "country"), ("l_extendedprice", "l_quantity"), tie)
    return ActivityTable(li.select(*schema.columns), schema, "lineitem")


def activity_conversations(spark: SparkSession, sf_dir: str) -> ActivityTable:
    c = load(spark, sf_dir, "conversations").withColumn("n_chars", F.length("text"))
    schema = ActivitySchema("conv_id", "turn", "role", (), ("n_chars",), (), "tick")
    return ActivityTable(c.select(*schema.columns), schema, "conversations")


def worked_example(spark: SparkSession) -> ActivityTable:
    """Ten tuples of three players of a game, small enough to check by hand."""
    # Tie, player, time, action, role, country, gold.
    rows = [
        (1, "001", "2013-05-19 10:00:00", "launch", "dwarf", "Australia", 0),
        (2, "001", "2013-05-20 08:00:00", "shop", "dwarf", "Australia", 50),
        (3, "001", "2013-05-20 14:00:00", "shop", "dwarf", "Australia", 100),
        (4, "001", "2013-05-21 14:00:00", "shop", "assassin", "Australia", 50),
        (5, "001", "2013-05-22 09:00:00", "fight", "assassin", "Australia", 0),
        (6, "002", "2013-05-20 09:00:00", "launch", "wizard", "United States", 0),
        (7, "002", "2013-05-21 15:00:00", "shop", "wizard", "United States", 30),
        (8, "002", "2013-05-22 17:00:00", "shop", "wizard", "United States", 40),
        (9, "003", "2013-05-20 10:00:00", "launch", "bandit", "China", 0),
        (10, "003", "2013-05-21 10:00:00", "fight", "bandit", "China", 0),
    ]
    df = spark.createDataFrame(rows, "tie int, player string, time string, action string, role string, country string, gold int").withColumn("time", F.col("time").cast("timestamp_ntz"))
    return ActivityTable(df, ActivitySchema("player", "time", "action", ("role", "country"), ("gold",), ("tie",)), "worked_example")


def scale_users(act: ActivityTable, factor: int) -> ActivityTable:
    """Every user ``factor`` times, under new ids: the replication that the experiments scale by."""
    copies = F.explode(F.sequence(F.lit(0), F.lit(factor - 1))).alias("_copy")
    user = act.schema.user
    is_text = isinstance(act.df.schema[user].dataType, T.StringType)
    new = F.concat(F.col(user), F.lit("-"), F.col("_copy")) if is_text else F.col(user) * factor + F.col("_copy")
    df = act.df.select("*", copies).withColumn(user, new).select(*act.df.columns)
    return act.with_df(df, layout="raw", birth_index=None, name=f"{act.name}_x{factor}")


def rank_in_user(act: ActivityTable) -> DataFrame:
    """Tuples with their place in their user's order."""
    s = act.schema
    return act.df.withColumn("place", F.row_number().over(Window.partitionBy(s.user).orderBy(s.time, *s.tie_break)))


class Catalog:
    """Names of activity tables."""

    def __init__(self) -> None:
        self._tables: dict[str, ActivityTable] = {}

    def register(self, name: str, table: ActivityTable) -> Catalog:
        self._tables[name.lower()] = table
        return self

    def __getitem__(self, name: str) -> ActivityTable:
        try:
            return self._tables[name.lower()]
        except KeyError:
            raise CohortSemanticError(f"no activity table {name!r}") from None

    def __contains__(self, name: str) -> bool:
        return name.lower() in self._tables


CANONICAL: dict[str, Callable[[SparkSession, str], ActivityTable]] = {
    "events": activity_events,
    "launch": activity_launch,
    "orders": activity_orders,
    "lineitem": activity_lineitem,
    "conversations": activity_conversations,
}

"""Moving objects, query sets and roads from the given tables.

Only + - * / and % on integers and correctly rounded doubles, so that any
engine gets the same bits. ``expressions`` are in Spark's dialect;
``kinetic.oracle`` turns them into DuckDB's.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Unit vectors by direction (fixed values).
UX = "1 -1 0 0 0.6 -0.6 0.6 -0.6 0.8 -0.8 0.8 -0.8 1 -1 0 0".split()
UY = "0 0 1 -1 0.8 0.8 -0.8 -0.8 0.6 0.6 -0.6 -0.6 0 0 1 -1".split()
#: Mean speeds of the three road classes, and the class of order priorities 1 to 5 by regime (fixed values).
SPEEDS = {1: "30.0", 2: "18.0", 3: "9.0"}
REGIMES = {"mix-L": "12233", "mix-S": "12333", "mix-B": "11123"}
COLUMNS = ["oid", "x", "y", "vx", "vy", "speed", "t_ref"]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _unit(values: list[str]) -> str:
    return "CASE dir " + " ".join(f"WHEN {i} THEN {float(v)}D" for i, v in enumerate(values)) + " END"


def orders_expressions(regime: str = "mix-L", any_direction: bool = False) -> list[dict[str, str]]:
    """Steps of columns over orders with their customer's nation; each step sees the ones before."""
    mu = "CASE substr(o_orderpriority, 1, 1) " + " ".join(f"WHEN '{i + 1}' THEN {SPEEDS[int(c)]}D" for i, c in enumerate(REGIMES[regime])) + " END"
    steps = [
        {"p": "cast(round(o_totalprice * 100) as bigint)", "dd": "datediff(o_orderdate, date'1995-01-01')", "n": "c_nationkey", "ck": "o_custkey", "oid": "o_orderkey"},
        {
            "u1": "(p % 9973) / 9973", "u2": "((p div 9973) % 5003) / 5003", "u3": "((p * 31 + dd * 17 + oid * 7) % 1009) / 1009", "u4": "((p * 13 + dd * 101 + oid * 3) % 1013) / 1013",
            "u5": "((p * 7 + dd * 53 + oid * 29) % 1019) / 1019", "u6": "((p * 3 + dd * 11 + oid * 59) % 1021) / 1021", "mu": mu, "dir": "(p + 7 * dd + ck) % 16",
            "a": "2 * ((p * 17 + oid * 5) % 997) / 997 - 1", "b": "2 * ((p * 23 + dd * 3 + oid) % 991) / 991 - 1",
        },
        {"w1": "2 * u1 - 1", "w2": "2 * u2 - 1", "speed": "greatest(0.5D, mu + 10 * 1.7320508075688772D * (u3 + u4 + u5 + u6 - 2))"},
        {"x": "1000 + 2000 * (n % 5) + 1000 * w1 * w1 * w1", "y": "1000 + 2000 * (n div 5) + 1000 * w2 * w2 * w2", "ux": "a / sqrt(a * a + b * b)" if any_direction else _unit(UX), "uy": "b / sqrt(a * a + b * b)" if any_direction else _unit(UY)},
        {"vx": "speed * ux", "vy": "speed * uy", "t_ref": "0.0D"},
    ]
    return steps


def lineitem_expressions() -> list[dict[str, str]]:
    return [
        {"p": "cast(round(l_extendedprice * 100) as bigint)", "h": "l_suppkey % 25", "speed": "l_quantity"},
        {"u1": "(p % 9973) / 9973", "u2": "((p div 9973) % 5003) / 5003", "dir": "(l_partkey + p) % 16"},
        {"w1": "2 * u1 - 1", "w2": "2 * u2 - 1"},
        {"x": "1000 + 2000 * (h % 5) + 1000 * w1 * w1 * w1", "y": "1000 + 2000 * (h div 5) + 1000 * w2 * w2 * w2", "ux": _unit(UX), "uy": _unit(UY)},
        {"vx": "speed * ux", "vy": "speed * uy", "t_ref": "0.0D"},
    ]


def events_expressions(rush: bool = False) -> list[dict[str, str]]:
    lift = " * (1.0D + CASE WHEN hr BETWEEN 11 AND 13 OR hr BETWEEN 19 AND 22 THEN 0.5D WHEN hr BETWEEN 2 AND 5 THEN -0.5D ELSE 0.0D END)" if rush else ""
    return [
        {"us": "unix_micros(ts)", "k": "cast(get_json_object(props, '$.k') as int)", "hr": "hour(ts)"},
        {"u1": "(us % 9973) / 9973", "u2": "((us div 9973) % 5003) / 5003", "speed": f"value / 5{lift}", "dir": "k % 16"},
        {"w1": "2 * u1 - 1", "w2": "2 * u2 - 1"},
        {"x": "500 + 1000 * (k % 10) + 500 * w1 * w1 * w1", "y": "500 + 1000 * (k div 10) + 500 * w2 * w2 * w2", "ux": _unit(UX), "uy": _unit(UY)},
        {"vx": "speed * ux", "vy": "speed * uy", "t_ref": "0.0D"},
    ]


def embed_expressions() -> list[dict[str, str]]:
    e = {f"e{i}": f"cast(embedding[{i - 1}] as double)" for i in range(1, 5)}
    return [
        {"oid": "vec_id", **e},
        {"x": "least(10000.0D, greatest(0.0D, 5000 + 12000 * e1))", "y": "least(10000.0D, greatest(0.0D, 5000 + 12000 * e2))", "vx": "100 * e3", "vy": "100 * e4", "t_ref": "0.0D"},
        {"speed": "sqrt(vx * vx + vy * vy)"},
    ]


def range_expressions(window: int, t: int) -> list[dict[str, str]]:
    return [
        {"qid": "s_suppkey", "p": "cast(round(s_acctbal * 100) as bigint) + 200000"},
        {"xlo": f"((p * 7 + qid * 101) % 9973) / 9973 * (10000 - {window})", "ylo": f"((p * 13 + qid * 307) % 9967) / 9967 * (10000 - {window})"},
        {"xhi": f"xlo + {window}", "yhi": f"ylo + {window}", "t": f"{t}.0D"},
    ]


def knn_expressions(k: int, t: int, key: str = "n_nationkey") -> list[dict[str, str]]:
    return [
        {"qid": f"cast({key} as bigint)"},
        {"cx": "((qid * 7919 + 37) % 9973) / 9973 * 10000", "cy": "((qid * 6101 + 11) % 9967) / 9967 * 10000", "k": str(k), "t": f"{t}.0D"},
    ]


def _steps(df: DataFrame, steps: list[dict[str, str]]) -> DataFrame:
    for step in steps:
        df = df.withColumns({name: F.expr(e) for name, e in step.items()})
    return df


def _once(df: DataFrame, *columns: str) -> DataFrame:
    """The columns behind a generator of one row: filters on them are not rewritten over the steps below, which would repeat every step for every use."""
    return df.select(F.inline(F.array(F.struct(*columns))))


def mo_orders(spark: SparkSession, sf_dir: str, regime: str = "mix-L", any_direction: bool = False) -> DataFrame:
    """Vehicles of a city: positions round 25 hubs, three speed classes by regime, 16 directions or any."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderdate", "o_orderpriority")
    customers = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    rows = _steps(orders.join(customers, F.col("o_custkey") == F.col("c_custkey")), orders_expressions(regime, any_direction))
    return _once(rows, *COLUMNS)


def mo_lineitem(spark: SparkSession, sf_dir: str, m: int | None = None, keep_sixth: bool = False) -> DataFrame:
    """The set that scales: 50 speeds; ``m`` sixths of the rows, those whose ``sixth`` is below.

    The id packs the columns that tell rows apart into a hash, so that no
    ordering of all rows is needed.
    """
    rows = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_shipdate")
    rows = rows.withColumn("sixth", F.expr("(l_partkey * 7 + l_suppkey) % 6"))
    if m is not None:
        rows = rows.where(F.col("sixth") < m)
    oid = F.expr("l_orderkey * 1000003 + cast(l_linenumber as bigint) * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + cast(round(l_extendedprice * 100) as bigint) * 15485863 + cast(l_quantity as bigint) * 32452843 + cast(datediff(l_shipdate, date'1992-01-01') as bigint) * 49979687")
    return _once(_steps(rows.withColumn("oid", oid), lineitem_expressions()), *COLUMNS, *(["sixth"] if keep_sixth else []))


def mo_events(spark: SparkSession, sf_dir: str, rush: bool = False, one_object_per_event: bool = False) -> DataFrame:
    """Status updates of taxis; ``rush`` injects a peak at noon and night."""
    rows = _steps(read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")), events_expressions(rush))
    rows = rows.withColumn("oid", F.col("event_id" if one_object_per_event else "user_id"))
    return _once(rows, *COLUMNS, "ts", "hr", "event_id")


def mo_embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Objects with continuous, nearly normal velocities."""
    return _once(_steps(read(spark, sf_dir, "embeddings").select("vec_id", "embedding"), embed_expressions()), *COLUMNS)


def q_range(spark: SparkSession, sf_dir: str, window: int = 400, t: int = 60) -> DataFrame:
    """Predictive range queries: a square window at a time."""
    return _steps(read(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal"), range_expressions(window, t)).select("qid", "xlo", "ylo", "xhi", "yhi", "t")


def q_knn(spark: SparkSession, sf_dir: str, k: int = 30, t: int = 60) -> DataFrame:
    """Predictive nearest-neighbour queries: a centre, k, and a time."""
    return _steps(read(spark, sf_dir, "nation").select("n_nationkey"), knn_expressions(k, t)).select("qid", "cx", "cy", "k", "t")

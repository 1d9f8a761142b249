"""The experiments' point sets, re-expressed on the given tables; and the same as DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkspan.session import Workspace

DAY = "datediff({0}, date'1970-01-01')", "datediff('day', date '1970-01-01', cast({0} as date))"
SECONDS = "unix_seconds(cast({0} as timestamp))", "cast(epoch_us({0}) // 1000000 as bigint)"
JSON_K = "cast(get_json_object(props, '$.k') as bigint)", "cast(json_extract_string(props, '$.k') as bigint)"
FIXED = "cast(round({0} * {1}) as bigint)"
LINE_ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity, l_discount, l_tax, l_shipdate, l_returnflag, l_linestatus"


def _hex(salt: str, at: int, length: int, engine: int) -> str:
    text = f"md5(concat('{salt}', cast(o_orderkey as {'string' if engine == 0 else 'varchar'})))" if salt else f"md5(cast(o_orderkey as {'string' if engine == 0 else 'varchar'}))"
    part = f"substr({text}, {at}, {length})"
    return f"cast(conv({part}, 16, 10) as bigint)" if engine == 0 else f"cast(concat('0x', {part}) as bigint)"


def _normal(axis: int, engine: int) -> str:
    parts = [_hex(f"{axis}-{i}-", at, 4, engine) for i in range(2) for at in (1, 5, 9, 13, 17, 21)]
    return f"({' + '.join(parts)}) - 393210"


def _uniform(axis: int, engine: int) -> str:
    return f"{_hex('', 1 + 5 * axis, 5, engine)} - 524288"


def _sets(e: int) -> dict[str, tuple[str, str, list[str], str]]:
    """name: (table, pid, coordinates, filter). e: 0 Spark, 1 DuckDB."""
    sec, k, day = SECONDS[e].format("ts"), JSON_K[e], DAY[e].format("l_shipdate")
    fixed = lambda c, s: FIXED.format(c, s)
    entry = lambda i: fixed(f"cast(embedding[{i if e == 0 else i + 1}] as double)", 1000000)
    line = f"row_number() over (order by {LINE_ORDER})"
    return {
        "highway2d": ("events", "event_id", [sec, fixed("value", 1000)], "event_type in ('click', 'purchase', 'view')"),
        "highway2d_one": ("events", "event_id", [sec, fixed("value", 1000)], "event_type = 'purchase'"),
        "taxi2d": ("events", "event_id", [sec, fixed("value", 1000)], ""),
        "road2d": ("customer", "c_custkey", [fixed("c_acctbal", 100), "cast(c_nationkey as bigint) * 10000"], ""),
        "geo3d": ("events", "event_id", [fixed("value", 100), f"{sec} % 86400", f"{k} * 100"], ""),
        "lattice3d": ("lineitem", line, [fixed("l_quantity", 1), fixed("l_discount", 100), fixed("l_tax", 100)], ""),
        "cosmo3d": ("lineitem", line, [fixed("l_quantity", 1000), fixed("l_extendedprice", 100), f"cast({day} as bigint) * 1000"], ""),
        "varied2d": ("embeddings", "vec_id", [entry(0), entry(1)], ""),
        "varied3d": ("embeddings", "vec_id", [entry(0), entry(1), entry(2)], ""),
        "normal2d": ("orders", "o_orderkey", [_normal(0, e), _normal(1, e)], ""),
        "normal3d": ("orders", "o_orderkey", [_normal(a, e) for a in range(3)], ""),
        "uniform2d": ("orders", "o_orderkey", [_uniform(0, e), _uniform(1, e)], ""),
        "uniform3d": ("orders", "o_orderkey", [_uniform(a, e) for a in range(3)], ""),
        "price1d": ("orders", "o_orderkey", [fixed("o_totalprice", 100)], ""),
        "chars1d": ("documents", "doc_id", ["cast(n_chars as bigint)"], ""),
        "supplier2d": ("supplier", "s_suppkey", [fixed("s_acctbal", 100), "cast(s_nationkey as bigint) * 10000"], ""),
    }


NAMES = list(_sets(0))


def numbered(df: DataFrame, order: list[str], name: str, work: Workspace) -> DataFrame:
    """Rows with their place (from 1) in the total order, without one task that sorts them all: ranges are
    sorted side by side and written with the place within each; one row per range gives the offsets."""
    at = F.monotonically_increasing_id()
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order)
    kept = work.save(ranged.select("*", F.shiftright(at, 33).alias("__range"), at.bitwiseAND(F.lit((1 << 33) - 1)).alias("__at")))
    sizes = kept.groupBy("__range").count().orderBy("__range").collect()  # as many rows as the exchange had parts
    before, rows = 0, []
    for r in sizes:
        rows.append((r["__range"], before))
        before += r["count"]
    offsets = df.sparkSession.createDataFrame(rows, "__range bigint, __before bigint")
    return kept.join(F.broadcast(offsets), "__range").withColumn(name, F.col("__before") + F.col("__at") + 1).drop("__range", "__at", "__before")


def points(spark: SparkSession, sf_dir: str, name: str, where: str = "") -> DataFrame:
    table, pid, coords, keep = _sets(0)[name]
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    if keep:
        df = df.where(keep)
    if table == "lineitem":
        df, pid = numbered(df.select(*LINE_ORDER.split(", ")), LINE_ORDER.split(", "), "pid", Workspace(spark, "numbered")), "pid"
    out = df.selectExpr(f"cast({pid} as bigint) as pid", *[f"cast({c} as bigint) as x{i}" for i, c in enumerate(coords)])
    return out.where(where) if where else out


def points_sql(name: str, where: str = "") -> str:
    table, pid, coords, keep = _sets(1)[name]
    inner = f"select cast({pid} as bigint) as pid, {', '.join(f'cast({c} as bigint) as x{i}' for i, c in enumerate(coords))} from {table}" + (f" where {keep}" if keep else "")
    return f"select * from ({inner}) where {where}" if where else inner


def scale_sample(points_: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """n points in the order of a hash of (seed, pid): samples of one seed nest and can be repeated."""
    return points_.orderBy(F.md5(F.concat(F.lit(f"{seed}-"), F.col("pid").cast("string"))), "pid").limit(n)

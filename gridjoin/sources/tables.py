"""Reading the tables, and the joined or exploded sources that relations are projected from. Each source has its SQL."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A table; the scan reads only the columns that a plan uses."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """Temporary views of the tables, for the SQL front."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_text_formats(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """csv, json, orc or text with a stated schema, so nothing is read to infer one."""
    return spark.read.format(fmt).schema(schema).options(**({"header": "true"} if fmt == "csv" else {})).load(path)


def keys(df: DataFrame, by: str, name: str = "k") -> DataFrame:
    """df with generated ids, 0, 1, 2 and so on in the order of a column: rows are numbered in ranges as they are written, and each range begins where those before it end."""
    placed = staged(df.repartitionByRange(by).sortWithinPartitions(by).withColumn("__at", F.monotonically_increasing_id()), "keys")
    part = F.shiftright("__at", 33)
    first, starts = 0, []
    for r in placed.groupBy(part.alias("p")).count().orderBy("p").collect():
        starts.append((r["p"], first))
        first += r["count"]
    begins = df.sparkSession.createDataFrame(starts, "__p long, __first long")
    out = placed.join(F.broadcast(begins), part == F.col("__p"))
    return out.select(*df.columns, (F.col("__first") + F.col("__at").bitwiseAND((1 << 33) - 1)).alias(name))


def from_rows(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def stream_events(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).options(**({"header": "true"} if fmt == "csv" else {})).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, by: list[str]) -> None:
    """A table whose joins on ``by`` need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, *by).sortBy(*by).saveAsTable(table)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one where a local session names none (tests). On a cluster it must be named."""
    global _own_dir
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="gridjoin_")
        atexit.register(shutil.rmtree, _own_dir, ignore_errors=True)
    return f"file://{_own_dir}"


_own_dir: str | None = None


def staged(df: DataFrame, name: str) -> DataFrame:
    """df as a written table in the shared folder: several jobs read it, and a lost executor does not bring its lineage back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Bytes of scans from which frames are staged one after another.
LARGE = 1 << 28


def scanned(df: DataFrame) -> int:
    """Bytes of the tables that a frame reads."""
    leaves = df._jdf.queryExecution().analyzed().collectLeaves()
    return sum(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size()))


def staged_together(frames: list[DataFrame], name: str) -> list[DataFrame]:
    """staged() of several frames, a few jobs at a time; large ones each by itself, and what one shuffled may go before the next begins."""
    if sum(map(scanned, frames)) < LARGE:
        with ThreadPoolExecutor(4) as pool:
            return list(pool.map(lambda df: staged(df, name), frames))
    out = []
    for df in frames:
        out.append(staged(df, name))
        df.sparkSession.sparkContext._jvm.System.gc()
    return out


def drain(df: DataFrame) -> None:
    """Runs a plan and keeps nothing."""
    df.write.format("noop").mode("overwrite").save()


def _lo(s, d):
    return load(s, d, "lineitem").join(load(s, d, "orders"), F.expr("l_orderkey = o_orderkey"))


def _trade(s, d):
    lines = load(s, d, "lineitem").join(load(s, d, "orders"), F.expr("l_orderkey = o_orderkey"))
    return lines.join(load(s, d, "customer"), F.expr("o_custkey = c_custkey")).join(load(s, d, "supplier"), F.expr("l_suppkey = s_suppkey"))


def _supply(s, d):
    return load(s, d, "supplier").join(load(s, d, "nation"), F.expr("s_nationkey = n_nationkey"))


def _clients(s, d):
    return load(s, d, "customer").join(load(s, d, "nation"), F.expr("c_nationkey = n_nationkey"))


def _orders_of(s, d):
    return load(s, d, "orders").join(_clients(s, d), F.expr("o_custkey = c_custkey"))


def _doclabels(s, d):
    return load(s, d, "documents", ["doc_id", "lang", "source"]).join(load(s, d, "labels"), "doc_id")


#: ASCII white space, as both engines split.
SPACES = r"[ \t\n\r\f]+"


def _doctokens(s, d):
    return load(s, d, "documents", ["doc_id", "text"]).select("doc_id", F.explode(F.split(F.lower("text"), SPACES)).alias("w")).where("w <> ''")


def _itemtokens(s, d):
    return load(s, d, "benchmark").select("item_id", F.explode(F.split(F.lower("text"), SPACES)).alias("w")).where("w <> ''")


def _product(first: str, second: str):
    def build(s, d):
        lines = load(s, d, "lineitem")
        return lines.selectExpr(first).distinct().crossJoin(lines.selectExpr(second).distinct())

    return build


_Y = "l_orderkey * 100000 + l_partkey"
#: name: (DataFrame of it, SQL of it)
SOURCES = {
    "lo": (_lo, "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "trade": (_trade, "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
    "supply": (_supply, "supplier JOIN nation ON s_nationkey = n_nationkey"),
    "clients": (_clients, "customer JOIN nation ON c_nationkey = n_nationkey"),
    "orders_of": (_orders_of, "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"),
    "doclabels": (_doclabels, "documents JOIN labels USING (doc_id)"),
    "doctokens": (_doctokens, f"(SELECT * FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '{SPACES}')) AS w FROM documents) WHERE w <> '') AS doctokens"),
    "itemtokens": (_itemtokens, f"(SELECT * FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '{SPACES}')) AS w FROM benchmark) WHERE w <> '') AS itemtokens"),
    "status_pairs": (_product("l_linestatus", f"{_Y} AS y"), f"(SELECT DISTINCT l_linestatus FROM lineitem) AS a CROSS JOIN (SELECT DISTINCT {_Y} AS y FROM lineitem) AS b"),
    "status_parts": (_product("l_linestatus", "l_partkey"), "(SELECT DISTINCT l_linestatus FROM lineitem) AS a CROSS JOIN (SELECT DISTINCT l_partkey FROM lineitem) AS b"),
}


def source(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return SOURCES[name][0](spark, sf_dir) if name in SOURCES else load(spark, sf_dir, name)


def source_sql(name: str) -> str:
    return SOURCES[name][1] if name in SOURCES else name

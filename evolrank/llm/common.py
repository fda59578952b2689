"""Small helpers that several operators of this subpackage share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

# The six white-space characters of the contracts (space, tab to carriage return).
SPACES = " \t\n\x0b\x0c\r"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

SLICE_BYTES = 16 << 20  # of text that Python handles at once; a longer text stands alone

_PATHS: dict[int, tuple[DataFrame, str]] = {}  # written tables that are not released yet


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only.  Pure ASCII values take the fast built-in."""
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def text_of(df: DataFrame, column: str = "text") -> Column:
    return F.coalesce(df[column].cast("string"), F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors can reach.

    It is the session's ``spark.checkpoint.dir``; only where that is unset
    (single-machine tests) a temporary folder of this process stands in.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            return str(held.get())
        folder = tempfile.mkdtemp(prefix="evolrank-shared-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def materialise(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: lineage ends there.

    The files survive the loss of any executor.  They are removed by ``release``,
    or else when the driver process ends.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/evolrank-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_remove, spark, path)
    made = spark.read.schema(df.schema).parquet(path)
    _PATHS[id(made)] = (made, path)
    _free_shuffles(spark)
    return made


def release(*tables: DataFrame) -> None:
    """Delete tables of ``materialise`` once nothing that still has to run reads them."""
    for df in tables:
        made, path = _PATHS.pop(id(df))
        _remove(made.sparkSession, path)


def _free_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffle files of finished queries.

    It finds them when the driver's heap is collected, which may otherwise take
    half an hour; until then they fill the executors' disks.
    """
    spark.sparkContext._jvm.System.gc()


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may be gone already; a left-over folder does no harm
        pass


def broadcast_up_to(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast hint when the table has at most ``rows`` rows (counted), else none."""
    if df.limit(rows + 1).count() <= rows:
        return F.broadcast(df)
    return df


def slices(batch: pa.RecordBatch, column: int, most: int = SLICE_BYTES):
    """Parts of an Arrow batch with at most ``most`` bytes in a text column, or with one row."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends, at = np.cumsum(sizes), 0
    while at < len(batch):
        before = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + most, side="right")))
        yield batch.slice(at, to - at)
        at = to


def map_texts(docs: DataFrame, start, fields: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Stream (id, text) through Python in slices of Arrow batches; the id column passes untouched.

    ``start()`` runs once a task and returns a function from a list of texts
    (null read as empty) to a dict of Arrow arrays or lists, one for each field.
    """
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *T._parse_datatype_string(fields).fields])
    kinds = to_arrow_schema(schema)

    def run(batches):
        work = start()
        for b in (part for whole in batches for part in slices(whole, 1)):
            made = work(b.column(1).to_pylist())
            cols = [b.column(0).cast(kinds.field(0).type)]
            cols += [made[f.name] if isinstance(made[f.name], pa.Array) else pa.array(made[f.name], f.type) for f in list(kinds)[1:]]
            yield pa.RecordBatch.from_arrays(cols, schema=kinds)

    return docs.select(docs[id_col], text_of(docs, text_col)).mapInArrow(run, schema)

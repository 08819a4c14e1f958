"""Helpers shared by the text operators: Arrow kernels, checkpoint folder, table access."""

from __future__ import annotations

import gc
import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows handed to a kernel at once; bounds the Python strings alive in a worker.
SLICE_ROWS = 256


def arrow_map(df: DataFrame, make: Callable[[], Callable[[list[list]], list[list]]], schema: str) -> DataFrame:
    """Apply a columnar kernel to every row of ``df``, in slices of SLICE_ROWS rows.

    ``make`` runs once per task and returns a kernel; the kernel gets one Python list per input column and
    returns one list per column of ``schema`` (any number of rows).
    """
    out = _arrow_schema(df.sparkSession, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = make()
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                cols = kernel([c.to_pylist() for c in part.columns])
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, out, strict=True)], schema=out)

    return df.mapInArrow(run, schema)


def _arrow_schema(spark: SparkSession, ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the cluster's spark.checkpoint.dir; a folder of this machine only where Spark runs on this machine alone."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return
    folder = sc.getConf().get("spark.checkpoint.dir")
    if not folder and not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="ckpt-"))


def shared_folder(spark: SparkSession) -> str:
    ensure_checkpoint_dir(spark)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


def fresh(taken: DataFrame | list[str], *names: str) -> list[str]:
    """The names, each prolonged until no column of ``taken`` is called so (in either case)."""
    used, out = {c.lower() for c in (taken.columns if isinstance(taken, DataFrame) else taken)}, []
    for name in names:
        while name.lower() in used:
            name += "_"
        used.add(name.lower())
        out.append(name)
    return out


def remove_folder(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared checkpoint folder; the result survives lost executors.

    The driver then collects garbage, so that shuffle files (and checkpoints, where the cluster cleans them) of steps that
    nothing refers to any more go at once and not at some later collection.
    """
    ensure_checkpoint_dir(df.sparkSession)
    out = df.checkpoint(eager=True)
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return out


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions_of(spark: SparkSession, at_least: int = 1) -> int:
    return max(at_least, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Tables of ``dealt_table`` that are still there: name -> folder.
_DEALT: dict[str, str] = {}


def dealt_table(df: DataFrame, column: str, parts: int) -> DataFrame:
    """Write ``df`` as a bucketed table in the checkpoint folder and read it: joins on ``column`` leave its rows in place.

    The rows are not shuffled: each task writes a file for each bucket it has rows of.  The table stays until
    ``drop_dealt`` is called, as what reads it may be lazy.
    """
    import uuid

    spark = df.sparkSession
    name = f"dealt_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name}"
    df.write.bucketBy(parts, column).option("path", path).saveAsTable(name)
    _DEALT[name] = path
    out = spark.table(name)
    out.dealt = name
    return out


def drop_dealt(spark: SparkSession, df: DataFrame | None = None) -> None:
    """Remove the table ``df`` of ``dealt_table`` with its files, or all such tables of this process."""
    for name in [df.dealt] if df is not None else list(_DEALT):
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        remove_folder(spark, _DEALT.pop(name))

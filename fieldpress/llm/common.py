"""Helpers shared by the text operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: At most so many rows of a side are broadcast; beyond it operators use another way.
BROADCAST_ROWS = 200_000
#: An Arrow batch is handled in slices of about so many bytes.
SLICE_CHARS = 4_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a local one where it is unset and the master is local (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if spark.sparkContext.getCheckpointDir() is None:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="fieldpress-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cut the lineage: write to the shared folder and read it back. Survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files of a table made by ``written`` that nothing reads any more."""
    spark = df.sparkSession
    jvm, root = spark.sparkContext._jvm, shared_dir(spark)
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if root.removeprefix("file:").lstrip("/") in folder:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def unused(df: DataFrame, *stems: str) -> list[str]:
    """Column names made of the stems that clash with none of df's."""
    have = {c.lower() for c in df.columns}
    out = []
    for s in stems:
        while s.lower() in have:
            s += "_"
        have.add(s.lower())
        out.append(s)
    return out


def map_batches(df: DataFrame, work: Callable[[], Callable[[pa.RecordBatch], dict[str, Any]]], schema: T.StructType) -> DataFrame:
    """mapInArrow with a state per task: work() gives the function that turns a batch into columns."""
    from pyspark.sql.pandas.types import to_arrow_schema

    target = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        act = work()
        for batch in batches:
            for part in sliced(batch):
                cols = act(part)
                yield pa.RecordBatch.from_arrays([cols[f.name] if isinstance(cols[f.name], pa.Array) else pa.array(cols[f.name], f.type) for f in target], schema=target)

    return df.mapInArrow(run, schema)


def sliced(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Slices of bounded bytes, so that memory follows neither the rows of a batch nor long texts."""
    if batch.num_rows and batch.nbytes > SLICE_CHARS:
        step = max(1, int(batch.num_rows * SLICE_CHARS / batch.nbytes))
        for i in range(0, batch.num_rows, step):
            yield batch.slice(i, step)
    else:
        yield batch


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether df has at most so many rows; reads no more than needed to tell."""
    return df.limit(rows + 1).count() <= rows


def crc_bucket(doc_id: Any, n: int) -> Any:
    return F.crc32(F.col(doc_id).cast("string").cast("binary") if isinstance(doc_id, str) else doc_id.cast("string").cast("binary")) % n


def without(docs: DataFrame, ids: DataFrame, id_col: str | list[str]) -> DataFrame:
    """docs without the rows of these ids. The ids are broadcast if they are few (some 10 MB), else both sides are shuffled."""
    gone = written(ids.distinct(), "gone")
    return docs.join(F.broadcast(gone) if small(gone) else gone, id_col, "left_anti")

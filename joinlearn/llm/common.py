"""Helpers that the corpus operators share: shared-folder tables, Arrow batches, words."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Words of most contracts: runs of anything but the six ASCII white-space characters.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Texts are handed to Python code in runs of at most so many code points (one longer text goes alone).
RUN_CHARS = 4_000_000


def shared_folder(spark: SparkSession) -> str:
    """The folder all machines share: spark.checkpoint.dir. Where it is unset, a temporary one is made and set, in local mode only."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not folder:
        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        folder = "file://" + tempfile.mkdtemp(prefix="shared-")
        context.setCheckpointDir(folder)
    return folder.rstrip("/")


#: Folders that `cut` has written and nobody has dropped.
_written: list[str] = []


def cut(df: DataFrame, partition_by: str | None = None) -> DataFrame:
    """Write df as Parquet into the shared folder and read it again: lineage ends there and nothing is computed twice.

    A lost executor costs only its unfinished tasks; the written files stay readable for every other one. They stay until
    `drop_written` is told that no frame reads them any more."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    _written.append(path)
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def written() -> list[str]:
    """Folders of `cut` so far."""
    return list(_written)


def drop_written(spark: SparkSession, paths: list[str]) -> None:
    """Delete folders of `cut`; frames that read them must be done with."""
    for path in paths:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        _written.remove(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def crc_mod(name: str, m: int) -> Column:
    """crc32 of the id written as text, modulo m; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(name).cast("string"), F.lit("")).cast("binary")) % F.lit(m)


def word_count(name: str = "text") -> Column:
    """Number of white-space separated words without building them in Python: removes runs and counts what is left."""
    return F.length(F.regexp_replace(F.regexp_replace(text_or_empty(name), WORD_PATTERN, "\u0001"), r"[\x20\x09-\x0D]+", "")).cast("long")


def named(keep: list[str] | dict[str, str]) -> dict[str, str]:
    """Columns to carry along and the names they get; a list keeps its names."""
    return keep if isinstance(keep, dict) else {c: c for c in keep}


def masked(df: DataFrame) -> dict[str, str]:
    """All columns under names that no operator uses, for results that must not clash with them."""
    return {c: f"__in{i}" for i, c in enumerate(df.columns)}


def unmasked(df: DataFrame, names: dict[str, str]) -> DataFrame:
    return df.select(*[F.col(k).alias(c) for c, k in names.items()])


def _runs(batch: pa.RecordBatch, text_at: int | None) -> Iterator[pa.RecordBatch]:
    if text_at is None or batch.num_rows == 0:
        yield batch
        return
    import pyarrow.compute as pc

    lengths = pc.fill_null(pc.binary_length(batch.column(text_at)), 0).to_pylist()
    start = total = 0
    for i, n in enumerate(lengths):
        if i > start and total + n > RUN_CHARS:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    yield batch.slice(start)


def map_columns(df: DataFrame, columns: list, fn: Callable[[dict], dict], schema: str, text: str | None = "text", setup: Callable | None = None) -> DataFrame:
    """Apply fn to the given columns, in Arrow batches cut into runs of bounded text: {name: list} to {name: list}.

    setup, if given, runs once a task and its value is fn's second argument."""
    picked = df.select(*columns)
    names = picked.columns
    out = T._parse_datatype_string(schema)
    arrow = to_arrow_schema(out)
    text_at = names.index(text) if text else None

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = () if setup is None else (setup(),)
        for whole in batches:
            for batch in _runs(whole, text_at):
                if batch.num_rows == 0:
                    continue
                got = fn({n: batch.column(i).to_pylist() for i, n in enumerate(names)}, *made)
                yield pa.RecordBatch.from_arrays([pa.array(got[f.name], type=f.type) for f in arrow], schema=arrow)

    return picked.mapInArrow(task, out)

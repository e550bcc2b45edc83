"""What the operators share: stages in the shared folder, workers that see whole texts, shipped code."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructType

from windowforge.session import distilled, fresh_path, settled, ship as ship_code

__all__ = ["ascii_lower", "by_text", "distilled", "fresh_path", "fresh_name", "materialize", "ship", "table", "tidily"]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
materialize = settled

#: Rows that reach a Python worker at once: whole texts are long, and workers share an executor's memory.
ROWS_AT_ONCE = 2_000
#: Bytes of texts that a worker's function sees at once; one text may be longer.
BYTES_AT_ONCE = 16 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Gives executors this package's source, and bounds the rows that workers get at once."""
    ship_code(spark)
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > ROWS_AT_ONCE:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ROWS_AT_ONCE))


def fresh_name(df: DataFrame, name: str) -> str:
    """The name, made longer until no column has it (Spark tells no upper from lower case)."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name += "_"
    return name


def parts_of(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose last column, of strings, holds about that many bytes each."""
    ends, begin, held = batch.column(batch.num_columns - 1), 0, 0
    for k, size in enumerate(pc.binary_length(ends).to_pylist()):
        if held and held + size > most:
            yield batch.slice(begin, k - begin)
            begin, held = k, 0
        held += size
    if begin < batch.num_rows:
        yield batch.slice(begin)


def by_text(docs: DataFrame, id_col: str, text_col: str, schema: str, of: Callable[[], Callable[[list[str]], Iterable[tuple]]]) -> DataFrame:
    """Per row the id under its name and the fields of ``schema``, which a function tells from whole texts; null texts count as empty.

    ``of`` makes the function, once in each task. It gets the texts of some rows and gives a tuple for each. Ids never leave
    Arrow, so a null among them changes no other.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    told = StructType.fromDDL(schema)
    out = StructType([rows.schema["id"], *told.fields])
    kinds, most = [to_arrow_type(f.dataType) for f in told.fields], BYTES_AT_ONCE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tell = of()
        for batch in batches:
            for part in parts_of(batch, most):
                columns = list(zip(*tell(part.column(1).to_pylist()))) or [()] * len(kinds)
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, type=t) for c, t in zip(columns, kinds))], names=out.names)

    return rows.mapInArrow(tidily(run), out).withColumnRenamed("id", id_col)


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z and leaves every other character alone; null becomes the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


#: What modules want called when a task ends, such as emptying what they remember.
AT_END: list[Callable[[], None]] = []


def tidily(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The same function over batches, which at its end gives back what the worker's allocators still hold; workers live on for other stages."""

    def wrapped(batches: Iterator) -> Iterator:
        yield from run(batches)
        for forget in AT_END:
            forget()
        gc.collect()
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):
            ctypes.CDLL("libc.so.6").malloc_trim(0)

    return wrapped

"""Helpers shared by the training-data operators: Arrow scans, the shared folder, word tables, held-out folds."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..session import shared_folder

#: Rows of an Arrow batch that are turned into Python objects at once.
SLICE_ROWS = 256


def schema_of(ddl: str) -> T.StructType:
    """The Spark schema that a DDL string names."""
    return T.StructType.fromDDL(ddl)


def arrow_map(df: DataFrame, ddl: str, rows: Callable[..., dict[str, list]], start: Callable[[], object] | None = None) -> DataFrame:
    """Run ``rows`` over slices of the columns of ``df`` on the executors.

    ``rows`` gets one list per column of ``df`` (after what ``start`` returned, if given, made once per task)
    and returns one list or numpy array per column of ``ddl``; a slice may give any number of rows.
    """
    schema = schema_of(ddl)
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = (start(),) if start else ()
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                made = rows(*state, *(c.to_pylist() for c in part.columns))
                yield pa.RecordBatch.from_arrays([pa.array(made[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def arrow_fold(df: DataFrame, ddl: str, start: Callable[[], object], add: Callable[..., None], end: Callable[[object], dict[str, list]]) -> DataFrame:
    """Fold each partition of ``df`` into one state of bounded size and return what ``end`` makes of it."""
    schema = schema_of(ddl)
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = start()
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                add(state, *(c.to_pylist() for c in batch.slice(at, SLICE_ROWS).columns))
        made = end(state)
        yield pa.RecordBatch.from_arrays([pa.array(made[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def stored(df: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """``df`` written to the shared folder and read again: cuts lineage and survives the loss of executors.

    keep: if given, gets the path, so that the caller can remove it with ``remove``.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if keep is not None:
        keep.append(path)
    return spark.read.schema(df.schema).parquet(path)


def bitmap(numbers: DataFrame, cells: Callable[[np.ndarray], np.ndarray], bits: int) -> np.ndarray:
    """A bitmap of ``bits`` bits in which the cells of every number (the one LONG column) are marked.

    Marks are joined to words of 63 bits on the executors: at most bits / 63 rows reach the driver, whatever the table.
    """

    def words(x):
        at = np.unique(cells(np.array(x, dtype=np.int64)))
        word, start = np.unique(at // 63, return_index=True)
        return {"word": word, "mask": np.bitwise_or.reduceat(np.int64(1) << (at % 63), start) if len(at) else at}

    held = np.zeros(-(-bits // 63), dtype=np.int64)
    for batch in arrow_map(numbers, "word int, mask long", words).groupBy("word").agg(F.bit_or("mask")).toArrow().to_batches():
        held[batch.column(0).to_numpy()] = batch.column(1).to_numpy()
    # Opened a few words at a time, as the driver may have little memory; 8 words fill whole bytes.
    made = [np.packbits((held[at : at + 4096, None] >> np.arange(63) & 1).astype(np.uint8), bitorder="little") for at in range(0, len(held), 4096)]
    return np.concatenate(made)[: -(-bits // 8)]


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def fold(column: str, modulus: int):
    """crc32 of the id's decimal text, modulo ``modulus``: the fold of a document."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(modulus))


class WordTable(dict):
    """Remembers what ``make`` gives for a word; forgets all when it holds more than ``most`` words.

    ``table[word]`` runs in C for known words, so a text costs one dictionary lookup a word.
    """

    def __init__(self, make: Callable[[str], object], most: int = 400_000):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, word):
        value = self.make(word)
        if len(word) <= 64:
            self[word] = value
        return value

    def trim(self) -> None:
        if len(self) > self.most:
            self.clear()

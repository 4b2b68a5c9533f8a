"""What several operators share: input normalisation, row-wise bindings and batch iteration."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters that separate words.
SPACES = " \t\n\x0b\f\r"
SPACE_CLASS = r"[ \t\n\x0B\f\r]"
#: Bytes of text that array operators take at once: their arrays need some hundred times as much.
SLICE = 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows that go to a Python worker at once: Arrow buffers on both sides hold them, whatever the length of their texts.
BATCH_ROWS = 1000


def small_batches(df: DataFrame) -> DataFrame:
    """df, after lowering the session's rows a batch to BATCH_ROWS if they are more; this setting may change at any time."""
    name, conf = "spark.sql.execution.arrow.maxRecordsPerBatch", df.sparkSession.conf
    if not 0 < int(conf.get(name)) <= BATCH_ROWS:
        conf.set(name, str(BATCH_ROWS))
    return df


def id_and_text(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Only the two columns that are needed, whatever else the table has; a null text is empty."""
    return small_batches(docs).select(F.col(key).cast("long").alias(key), F.coalesce(F.col(text).cast("string"), F.lit("")).alias(text))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once a row: a lambda parameter isn't inlined, unlike a column."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def words_of(text: Column) -> Column:
    """Maximal runs of characters other than SPACES."""
    return let(
        F.trim(text, F.lit(SPACES)),
        lambda t: F.when(F.length(t) == 0, F.array().cast("array<string>")).otherwise(F.split(t, SPACE_CLASS + "+")),
    )


def columns_of(batch: pa.RecordBatch, *names: str) -> list[list]:
    return [batch.column(batch.schema.get_field_index(n)).to_pylist() for n in names]


def sliced(batches: Iterable[pa.RecordBatch], chars: int, text: str = "text") -> Iterator[pa.RecordBatch]:
    """Cut batches so that each holds about `chars` bytes of text, or one row if a single text is longer."""
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
        start, held = 0, 0
        for i, n in enumerate(sizes):
            if held and held + n > chars:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += int(n)
        if start < batch.num_rows:
            yield batch.slice(start)

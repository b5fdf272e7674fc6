"""What the operators share: tables, the definition of a word, keyed random numbers, rows as Arrow."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A word: a run of characters other than space and U+0009 to U+000D.
WORD = r"[^\x20\x09-\x0D]+"
#: The characters between words.
GAPS = " \t\n\x0b\x0c\r"
#: Rows that a step of arrow_map sees at once.
ROWS = 2000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
TO_LOWER = str.maketrans(UPPER, LOWER)
_GAPS_TO_SPACE = str.maketrans(dict.fromkeys("\t\n\x0b\x0c\r", " "))


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, cut to the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def ascii_lower(text: Column) -> Column:
    """A-Z to a-z and nothing else."""
    return F.translate(text, UPPER, LOWER)


def words_of(text: str) -> list[str]:
    """The words of a text, in order; str.split() alone would also break at other Unicode spaces."""
    return [w for w in text.translate(_GAPS_TO_SPACE).split(" ") if w]


def byte_words(text: str | None) -> list[bytes]:
    """The words of a text in UTF-8, A-Z in lower case; bytes are lowered and split by ASCII rules, which are the ones wanted."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def word_count(text: Column) -> Column:
    """Number of words; null counts as empty."""
    marks = F.regexp_replace(F.coalesce(text, F.lit("")), WORD, "w")
    return F.length(F.translate(marks, GAPS, "")).cast("long")


def fold_bucket(doc_id: Column, folds: int = 5) -> Column:
    """crc32 of the id's decimal text, modulo folds."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds))


def give_back() -> None:
    """Return to the system what this process has freed; idle workers stay alive beside those of the next stage."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def frugal(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run, a function over a task's batches, that gives memory back after the last one."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return whole


def arrow_map(df: DataFrame, make: Callable[[], Callable[[dict], dict]], schema: str | T.StructType, rows: int = ROWS) -> DataFrame:
    """Map slices of `rows` rows, given as columns, to columns. make() runs once per task and builds the state."""
    from pyspark.sql.pandas.types import to_arrow_schema

    struct = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
    target = to_arrow_schema(struct)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in (whole.slice(lo, rows) for whole in batches for lo in range(0, whole.num_rows, rows)):
            got = step({name: batch.column(i) for i, name in enumerate(batch.schema.names)})
            if got is not None:
                yield pa.RecordBatch.from_arrays([as_array(got[f.name], f.type) for f in target], schema=target)

    return df.mapInArrow(frugal(run), struct)


def as_array(values, kind: pa.DataType) -> pa.Array:
    if isinstance(values, pa.Array):
        return values if values.type == kind else values.cast(kind)
    return pa.array(values, kind)

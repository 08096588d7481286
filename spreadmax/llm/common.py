"""Words, bytes and column plumbing that the operators share."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: A word: a run of digits, ASCII letters in lower case and anything beyond ASCII.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_WORDS = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256)
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold_ascii(text: Column) -> Column:
    """A-Z to lower case, every other character untouched."""
    return F.translate(text, UPPER, LOWER)


def fold_bytes(text: bytes) -> bytes:
    return text.translate(_FOLD)


def words_of(text: bytes) -> list[bytes]:
    """The words (pattern WORD after folding A-Z) of UTF-8 bytes."""
    return text.translate(_WORDS).split()


def fresh(taken: list[str], *names: str) -> list[str]:
    """The names, each with as many underscores behind it as make it differ from the columns `taken`, whatever their case."""
    used, out = {c.lower() for c in taken}, []
    for name in names:
        while name.lower() in used:
            name += "_"
        used.add(name.lower())
        out.append(name)
    return out


def columns(df: DataFrame, names: list[str] | None = None) -> list[Column]:
    return [F.col(f"`{c}`") for c in (df.columns if names is None else names)]


def text_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of a text column; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def append_columns(
    df: DataFrame, inputs: list[str], fields: list[tuple[str, T.DataType]], maker: Callable[[], Callable]
) -> DataFrame:
    """All columns of `df` and the result columns `fields`, computed from `inputs`.

    `maker()` is called once per task and gives the function of a batch: it takes
    the Arrow arrays of `inputs` and returns one list or array per field. A column
    of `df` that has the name of a result column is replaced.
    """
    names = [n for n, _ in fields]
    work = df.select(*[F.col(f"`{c}`") for c in df.columns if c not in names or c in inputs])
    kept = [c for c in work.columns if c not in names]
    schema = T.StructType([*[work.schema[c] for c in kept], *[T.StructField(n, t) for n, t in fields]])

    def run(batches):
        step, arrow = None, None
        for batch in batches:
            step = step or maker()
            made = step(*[batch.column(batch.schema.get_field_index(c)) for c in inputs])
            arrow = arrow or _arrow_types(fields)
            made = [
                m if isinstance(m, pa.Array) and m.type == t else pa.array(m, type=t)
                for m, t in zip(made, arrow, strict=True)
            ]
            own = [batch.column(batch.schema.get_field_index(c)) for c in kept]
            yield pa.RecordBatch.from_arrays([*own, *made], names=[*kept, *names])

    return work.mapInArrow(run, schema)


def _arrow_types(fields: list[tuple[str, T.DataType]]) -> list[pa.DataType]:
    from pyspark.sql.pandas.types import to_arrow_type

    return [to_arrow_type(t) for _, t in fields]

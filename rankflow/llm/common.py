"""Helpers shared by the text operators."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from rankflow.storage import discard, held, shared_folder, written

__all__ = ["UPPER", "WS", "discard", "documents", "held", "let", "lower_ascii", "packed", "prefix", "require", "shared_folder", "unpacked", "windows", "with_fields", "words", "written"]

#: White space of the contracts: blank, tab, newline, vertical tab, form feed, return.
WS = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` evaluated once per row.

    A column named inside a higher-order function is re-evaluated for every
    element once the optimizer has inlined it; a lambda variable is not.
    """
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column) -> Column:
    """Maximal runs of characters outside :data:`WS`, in order."""
    blank = F.translate(F.coalesce(text, F.lit("")), WS[1:], " " * (len(WS) - 1))
    return F.array_remove(F.split(blank, " "), "")


def lower_ascii(text: Column) -> Column:
    """``A-Z`` to lower case; other letters stay.  Pure-ASCII text takes the fast path."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(
        F.translate(text, UPPER, UPPER.lower())
    )


def windows(items: Column, n: int) -> Column:
    """All runs of ``n`` neighbouring items as structs; empty if there are fewer."""
    count = F.greatest(F.size(items) - F.lit(n - 1), F.lit(0))
    return F.arrays_zip(*[F.slice(items, F.lit(k + 1), count).alias(f"w{k}") for k in range(n)])


def require(df: DataFrame, columns: Iterable[str]) -> None:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")


def packed(docs: DataFrame) -> DataFrame:
    """The rows as one column ``row``, so that no inner name can clash with one of theirs."""
    return docs.select(F.struct("*").alias("row"))


def prefix(docs: DataFrame) -> str:
    """Underscores, one more than any column begins with."""
    return "_" * (1 + max((len(c) - len(c.lstrip("_")) for c in docs.columns), default=0))


def unpacked(rows: DataFrame, columns: Iterable[str], made: dict[str, Column]) -> DataFrame:
    """The columns of ``row`` in their order, with those made: in place of one of that name, or after the others."""
    left = {name.lower(): value for name, value in made.items()}
    names = {name.lower(): name for name in made}
    out = [left.pop(c.lower()).alias(names[c.lower()]) if c.lower() in left else F.col("row").getField(c).alias(c) for c in columns]
    return rows.select(*out, *[value.alias(names[k]) for k, value in left.items()])


def with_fields(schema: StructType) -> StructType:
    """A copy to add fields to; ``df.schema`` itself is kept by ``df``."""
    return StructType([*schema.fields])


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")

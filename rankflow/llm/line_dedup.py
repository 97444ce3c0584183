"""Line dedup: drop lines that many documents share, but for one copy.

Lines are exploded and normalised once, keyed by a 128-bit hash, and counted by
distinct documents.  The keys over the threshold are joined back to the lines
that hold them.  Keys that hold over a thousandth of all such lines are at most a
thousand and are broadcast, so that no key of the other join is a hot one.
Each document gets the places of the lines that it loses.  Text moves only in the
last join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankflow.llm.common import WS, discard, held, let, lower_ascii, packed, require, unpacked, written

#: A key with over one in so many of the shared lines is hot; there can't be more hot keys than that.
HOT = 1000


def line_key(line: Column) -> Column:
    """The line without white space at its ends, ``A-Z`` lower-cased."""
    return lower_ascii(F.btrim(line, F.lit(WS)))


def _same_text(text: Column) -> Column:
    """Tells rows apart that repeat an id; equal rows lose the same lines."""
    return F.xxhash64(text)


def _lines(rows: DataFrame, min_chars: int, id_col: str, text_col: str) -> DataFrame:
    """``id, t, pos, key`` of every line that is long enough."""
    text = F.coalesce(F.col(f"row.{text_col}"), F.lit(""))
    found = rows.where(F.col(f"row.{id_col}").isNotNull()).select(F.col(f"row.{id_col}").alias("id"), _same_text(text).alias("t"), F.posexplode(F.split(text, "\n")).alias("pos", "line"))
    return found.where(F.char_length(F.btrim("line", F.lit(WS))) >= min_chars).select("id", "t", "pos", F.unhex(F.md5(line_key(F.col("line")))).alias("key"))


def _shared(lines: DataFrame, min_docs: int) -> DataFrame:
    return lines.groupBy("key").agg(F.count_distinct("id").alias("n_docs"), F.count(F.lit(1)).alias("n_lines"), F.max("id").alias("keeper")).where(F.col("n_docs") >= min_docs)


def shared_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(key, n_docs, n_lines, keeper)`` of keys found in ``min_docs`` documents or more; ``keeper`` is the largest id."""
    require(docs, [id_col, text_col])
    return _shared(_lines(packed(docs), min_chars, id_col, text_col), min_docs)


def dedup_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with the text reassembled from the kept lines, ``n_lines`` and ``n_dropped``.

    A null or empty text is one empty line and comes back empty.  Rows with a null
    id count for no key and keep all lines; rows that repeat an id are one
    document.  Columns ``n_lines`` and ``n_dropped`` of the input are replaced.
    """
    require(docs, [id_col, text_col])
    rows = packed(docs)
    lines = written(_lines(rows, min_chars, id_col, text_col), "lines")
    keys = written(_shared(lines, min_docs), "keys")
    every = keys.agg(F.sum("n_lines")).first()[0] or 0
    hot = F.col("n_lines") * HOT > every
    gone = F.col("id") != F.col("keeper")
    some = lines.join(F.broadcast(keys.where(hot).select("key", "keeper")), "key").where(gone)  # at most HOT keys
    others = lines.join(keys.where(~hot).select("key", "keeper"), "key").where(gone)
    lost = some.union(others.select(some.columns)).groupBy("id", "t").agg(F.collect_set("pos").alias("lost"))
    lost = written(lost, "lost")
    discard(lines, keys)
    text = F.coalesce(F.col(f"row.{text_col}"), F.lit(""))
    # a set difference by hashing: linear in the lines, however many are lost
    kept = lambda s: F.transform(F.array_except(F.sequence(F.lit(0), F.size(s) - 1), F.col("lost")), lambda i: s[i])
    keyed = rows.select("row", F.col(f"row.{id_col}").alias("id2"), _same_text(text).alias("t2"))
    joined = keyed.join(lost, (F.col("id2") == F.col("id")) & (F.col("t2") == F.col("t")), "left")
    n_lines = F.octet_length(text) - F.octet_length(F.replace(text, F.lit("\n"), F.lit(""))) + 1
    made = {
        "n_lines": n_lines.cast("long"),
        "n_dropped": F.coalesce(F.size("lost"), F.lit(0)).cast("long"),
        text_col: F.when(F.col("lost").isNull(), text).otherwise(F.array_join(let(F.split(text, "\n"), kept), "\n")),
    }
    order = [c for c in docs.columns if c.lower() not in ("n_lines", "n_dropped")]
    return held(unpacked(joined, order, {text_col: made[text_col], "n_lines": made["n_lines"], "n_dropped": made["n_dropped"]}), lost)

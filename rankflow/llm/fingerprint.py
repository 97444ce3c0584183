"""Document fingerprints: one-permutation MinHash, densified, packed to low-order bits.

Each five-word shingle is hashed once; its top bits choose a bin, and a bin
keeps its least hash.  An empty bin borrows from the first full bin on a walk
that depends on the bin alone, so that empty bins of two texts borrow alike.
Four bits of each bin are kept as one hexadecimal digit; agreement by chance is
taken off when two fingerprints are compared.
"""

from __future__ import annotations

import json
import math
import random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.llm.common import let, packed, prefix, require, unpacked, windows, words

BINS_LOG2 = 8
BITS = 4
SHINGLE = 5
#: Steps of a walk that are laid out; beyond them the full bin of least keyed hash lends.
STEPS = 8
#: Most rows of a table that is broadcast here: two longs each.
BROADCAST_ROWS = 1_000_000


def walks(bins: int, seed: int = 7) -> list[list[int]]:
    """The first steps of each bin's walk over the others."""
    return [random.Random(seed * 1_000_003 + b).sample([x for x in range(bins) if x != b], min(STEPS, bins - 1)) for b in range(bins)]


def shingle_hashes(text: Column, n: int = SHINGLE) -> Column:
    """64-bit hashes of the runs of ``n`` words; a shorter text is one shingle, an empty one has none."""

    def hashes(w: Column) -> Column:
        whole = F.when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))
        return F.when(F.size(w) >= n, F.transform(windows(w, n), lambda x: F.xxhash64(x))).otherwise(whole)

    return let(words(text), hashes)


def _bin(h: Column, log2: int) -> Column:
    return F.shiftrightunsigned(h, 64 - log2).cast("int")


def _least(hashes: Column, log2: int) -> Column:
    """``(bin, digit)`` of each full bin's least hash."""

    def firsts(s: Column) -> Column:
        behind = F.concat(F.array(F.lit(None).cast("bigint")), F.slice(s, 1, F.greatest(F.size(s) - 1, F.lit(0))))
        pick = F.zip_with(s, behind, lambda x, y: F.when(y.isNull() | (_bin(x, log2) != _bin(y, log2)), x))
        full = F.filter(pick, lambda x: x.isNotNull())
        return F.transform(full, lambda x: F.struct(_bin(x, log2).alias("b"), x.bitwiseAND(F.lit((1 << BITS) - 1)).cast("int").alias("d")))

    return let(F.sort_array(hashes), firsts)


def fingerprint(text: Column, log2: int = BINS_LOG2, n: int = SHINGLE) -> Column:
    """One hexadecimal digit for each of ``2 ** log2`` bins; the empty string for a text without words."""
    bins = 1 << log2
    steps = F.from_json(F.lit(json.dumps(walks(bins))), "array<array<int>>")
    every = F.sequence(F.lit(0), F.lit(bins - 1))

    def lent(full: Column, by_bin: Column, b: Column) -> Column:
        near = let(F.element_at(steps, b + 1), lambda w: F.coalesce(*[by_bin[w[k]]["d"] for k in range(min(STEPS, bins - 1))]))
        far = F.array_min(F.transform(full, lambda x: F.struct(F.xxhash64(b, x["b"]).alias("h"), x["d"].alias("d"))))["d"]
        return F.coalesce(near, far)

    def dense(full: Column) -> Column:
        gaps = F.array_except(every, F.transform(full, lambda x: x["b"]))
        both = F.concat(full, F.transform(gaps, lambda b: F.struct(b.alias("b"), F.lit(None).cast("int").alias("d"))))
        digits = let(F.sort_array(both), lambda at: F.transform(at, lambda x: F.coalesce(x["d"], lent(full, at, x["b"]))))
        return F.array_join(F.transform(digits, lambda d: F.substring(F.lit("0123456789abcdef"), d + 1, F.lit(1))), "")

    return let(_least(shingle_hashes(text, n), log2), lambda full: F.when(F.size(full) == 0, F.lit("")).otherwise(dense(full)))


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard similarity of two fingerprints, 0 to 1; two empty ones are alike."""
    same = F.size(F.filter(F.zip_with(F.split(a, ""), F.split(b, ""), lambda x, y: x == y), lambda x: x))
    chance = 1 / (1 << BITS)
    share = (same / F.char_length(a) - chance) / (1 - chance)
    return F.when(a == b, F.lit(1.0)).when((a == "") | (b == ""), F.lit(0.0)).otherwise(F.greatest(share, F.lit(0.0)))


def _before(keys: DataFrame, bits: int, low: int, high: int) -> DataFrame:
    """``(k, p)``: each of the distinct integers ``k`` and the next lower one, in groups of ``2 ** bits`` values."""
    if high - low < 2 << bits:
        return keys.select("k", F.lag("k").over(Window.partitionBy(F.lit(0)).orderBy("k")).alias("p"))  # one group, of so many values
    group = F.shiftright("k", bits)
    inner = keys.select("k", group.alias("g"), F.lag("k").over(Window.partitionBy(group).orderBy("k")).alias("p"))
    tops = keys.groupBy(group.alias("g")).agg(F.max("k").alias("top"))
    above = _before(tops.select(F.col("g").alias("k")), bits, low >> bits, high >> bits)
    above = above.join(tops, above.p == tops.g, "left").select(F.col("k").alias("g"), "top")
    return inner.join(above, "g").select("k", F.coalesce("p", "top").alias("p"))


def with_next(docs: DataFrame, carried: list[str], id_col: str = "doc_id") -> DataFrame:
    """``docs`` with ``next_<c>`` for each carried column: its value in the row of the next lower id.

    The row of the lowest id is followed by that of the highest; a row without id
    by none.  Rows move once, to groups of neighbouring ids that are bounded by
    about the square root of their number, whatever the ids are.  A group also gets
    the row that follows its last one.  Rows of one id stand in order of ``carried``.
    Columns of the input that have a name of the new ones are replaced.
    """
    require(docs, [id_col, *carried])
    own = prefix(docs)  # inner names begin with what no column begins with
    nothing = {f"next_{c}": F.lit(None).cast(docs.schema[c].dataType) for c in carried}
    docs = docs.drop(*nothing)
    known, lost = docs.where(F.col(id_col).isNotNull()), docs.where(F.col(id_col).isNull())
    n, low, high = known.agg(F.count(F.lit(1)), F.min(id_col), F.max(id_col)).first()
    if not n:
        return docs.withColumns(nothing)
    bits = max(8, math.ceil(math.log2(n) / 2))
    group = F.shiftright(F.col(id_col).cast("bigint"), bits)
    tops = known.groupBy(group.alias("k")).agg(F.max(id_col).alias("top"))
    before = _before(tops.select("k"), bits, low >> bits, high >> bits)
    last = F.coalesce("p", F.lit(high >> bits).cast("bigint"))
    guests = before.select(F.col("k").alias(f"{own}to"), last.alias("p")).join(tops.select(F.col("k").alias("p"), F.col("top").alias(f"{own}guest")), "p").drop("p")
    few = guests.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    sent = known.join(F.broadcast(guests) if few else guests, F.col(id_col) == F.col(f"{own}guest"), "left")
    # a guest comes once, though its group may be its own
    late = F.when(F.col(f"{own}guest").isNotNull(), F.struct(F.col(f"{own}to").alias("g"), F.lit(1).alias("late")))
    sent = sent.withColumn(f"{own}at", F.explode(F.array_compact(F.array(F.struct(group.alias("g"), F.lit(0).alias("late")), late)))).drop(f"{own}to", f"{own}guest")
    order = Window.partitionBy(f"{own}at.g").orderBy(f"{own}at.late", F.col(id_col).desc(), *carried)
    out = sent.withColumns({f"next_{c}": F.lead(c).over(order) for c in carried}).where(F.col(f"{own}at.late") == 0).drop(f"{own}at")
    return out.unionByName(lost.withColumns(nothing))


def fingerprint_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with ``fingerprint``; a null text counts as empty.  Replaces a column of that name."""
    require(docs, [id_col, text_col])
    return unpacked(packed(docs), docs.columns, {"fingerprint": fingerprint(F.coalesce(F.col(f"row.{text_col}"), F.lit("")))})


def compare_with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of each text, of the text with its last third replaced, and how alike they and the next one's are."""
    base = fingerprint_documents(docs.select(id_col, F.coalesce(F.col(text_col), F.lit("")).alias("text")), id_col)
    made = with_next(base, ["text", "fingerprint"], id_col).withColumn("n_chars", F.char_length("text").cast("long"))
    third = F.floor(F.col("n_chars") / 3).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), F.col("n_chars").cast("int") - third), F.substring(F.coalesce("next_text", F.lit("")), F.lit(1), third))
    made = made.withColumn("edited", edited).withColumn("edited_fingerprint", fingerprint(F.col("edited")))
    return made.select(
        id_col, "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint",
        likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"),
        likeness(F.col("fingerprint"), F.coalesce("next_fingerprint", F.lit(""))).alias("near_next"),
    )

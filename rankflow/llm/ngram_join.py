"""Similarity join on word n-grams: a sparse product of documents by n-grams, in blocks.

Row ``d`` of the incidence matrix holds the hashes of a document's shingles.
Two documents link when ``den * overlap >= num * union``; overlaps are the
entries of the matrix times its transpose.  The product is never formed:

* equal rows are one class, and only its representative takes part;
* of each row only the head in a global order (rare shingles first) is
  multiplied: rows that link share a shingle within heads of
  ``n - ceil(n * num / den) + 1``;
* an entry of that product is discarded when sizes are too far apart, or when too
  few shingles are left after the shared one to reach the overlap that the
  sizes ask for;
* columns are multiplied by blocks.  First each column's purest row with all
  others, so that groups of near copies fall into one component from a number of
  entries in proportion to their size; then, for every column that still
  holds rows of different components, all pairs of blocks of its rows, but for
  pairs of one component.

* a pair that remains is discarded when histograms of its rows' hashes, bucket by
  bucket, add up to less than that overlap.

What remains has its overlap counted in full.  So no link between different
components is lost, whatever the order, and no step expands a group into pairs
that are known to be connected.
"""

from __future__ import annotations

import contextlib
import re
from collections.abc import Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow.llm.common import WS, discard, held, packed, require, unpacked, written

SHINGLE = 3
#: 100 * overlap >= 90 * union.
THRESHOLD = (90, 100)
#: Documents from which frequent shingles are learned: one in SHARE, and SAMPLE at least.  Only the order of shingles
#: depends on them, never a result; the share keeps what counts as frequent alike, however many documents there are.
SAMPLE, SHARE = 24_000, 32
#: Frequent shingles that go last, at most; sent to the workers.
FREQUENT = 100_000
#: Rows in a block of a column.
BLOCK = 512
#: Texts that a worker takes at a time, rows that it is sent at a time, and word hashes that it keeps.
TEXTS, ROWS, WORDS = 64, 1000, 100_000
_CAPITALS = re.compile("[A-Z]+")

#: Buckets of a row's histogram of hashes; a count of FULL stands for that many or more.
BUCKETS, FULL = 256, 255


class Words(dict):
    """64-bit hashes of words, kept."""

    def __init__(self):
        import xxhash

        super().__init__()
        self.digest = xxhash.xxh3_64_intdigest

    def __missing__(self, word: str) -> int:
        if len(self) >= WORDS:
            self.clear()
        found = self[word] = self.digest(word.encode())
        return found


class Hasher:
    """Sorted distinct 64-bit hashes of texts' shingles, many texts at a time."""

    def __init__(self, n: int = SHINGLE):
        import numpy as np

        self.np, self.n, self.known = np, n, Words()

    def mixed(self, x):
        """Spread the bits of 64-bit numbers; a bijection."""
        np = self.np
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))

    def runs(self, h, n: int):
        np = self.np
        out = np.full(len(h) - n + 1, n, np.uint64)
        for k in range(n):
            out = self.mixed(out * np.uint64(0x9E3779B97F4A7C15) + h[k : k + len(out)])
        return out

    def words(self, text: str | None) -> list[str]:
        text = text or ""
        text = text.lower() if text.isascii() else _CAPITALS.sub(lambda m: m[0].lower(), text)
        for blank in WS[1:]:
            text = text.replace(blank, " ")
        return [w for w in text.split(" ") if w]

    def shingles(self, texts: list[str | None]) -> list:
        """A sorted array for each text."""
        np = self.np
        lists = [self.words(t) for t in texts]
        h = np.fromiter((x for w in lists for x in map(self.known.__getitem__, w)), np.uint64, sum(map(len, lists)))
        every = self.runs(h, self.n) if len(h) >= self.n else h[:0]
        out, at = [], 0
        for w in lists:
            k = len(w)
            own = every[at : at + k - self.n + 1] if k >= self.n else self.runs(h[at : at + k], k) if k else h[:0]
            own = np.sort(own)
            out.append(own[np.concatenate(([True], own[1:] != own[:-1]))] if len(own) else own)
            at += k
        return out


def _needed(a: Column, b: Column, num: int, den: int) -> Column:
    """The overlap that two sizes ask for."""
    return F.ceil((a + b) * num / (num + den))


def frequent(docs: DataFrame, n: int) -> dict[int, int]:
    """Shingles that occur in several of the sampled documents, with how many: the most frequent, in bounded number."""
    total = docs.count()
    share = min(1 << 20, (max(SAMPLE, total // SHARE) << 20) // max(1, total) + 1)
    sample = docs.where(F.pmod(F.xxhash64("id", F.lit(5)), F.lit(1 << 20)) < share)

    def counted(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        own = Hasher(n)
        for whole in batches:
            for batch in (whole.slice(k, 4 * TEXTS) for k in range(0, whole.num_rows, 4 * TEXTS)):
                h, k = np.unique(np.concatenate(own.shingles(batch.column("text").to_pylist())), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(k.astype(np.int64))], names=["h", "k"])

    counts = sample.mapInArrow(counted, "h bigint, k bigint").groupBy("h").agg(F.sum("k").alias("k")).where("k >= 3")
    return {r["h"]: r["k"] for r in counts.orderBy(F.desc("k"), "h").limit(FREQUENT).collect()}


def signatures(docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """``id, n_shingles, d1, d2, head, histogram``.

    The size, a 128-bit digest of the set, its first shingles in the global order,
    and how many of its hashes fall into each bucket.
    """
    often = frequent(docs, n)
    late_keys = sorted(often)
    late_ranks = [often[h] for h in late_keys]

    def sign(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        own = Hasher(n)
        late = np.array(late_keys, np.int64).view(np.uint64)
        order = np.argsort(late)
        late, rank = late[order], np.array(late_ranks, np.int64)[order]
        maybe = np.zeros(1 << 20, bool)
        maybe[late & np.uint64(0xFFFFF)] = True

        def head(h, keep: int):
            some = np.flatnonzero(maybe[h & np.uint64(0xFFFFF)]) if len(late) else ()
            if len(some):
                at = np.minimum(np.searchsorted(late, h[some]), len(late) - 1)
                real = late[at] == h[some]
                some, by = some[real], rank[at[real]]
            if not len(some):
                return h[:keep]
            first = np.ones(len(h), bool)
            first[some] = False
            first = h[first][:keep]
            return first if len(first) == keep else np.concatenate((first, h[some][np.lexsort((h[some], by))]))[:keep]

        for whole in batches:
            for batch in (whole.slice(k, TEXTS) for k in range(0, whole.num_rows, TEXTS)):
                sets = own.shingles(batch.column("text").to_pylist())
                size = np.array([len(h) for h in sets], np.int64)
                flat = np.concatenate(sets)
                row = np.repeat(np.arange(len(sets)), size)
                full = np.flatnonzero(size)
                digests = np.zeros((2, len(sets)), np.uint64)
                if len(full):
                    starts = (np.cumsum(size) - size)[full]
                    digests[0, full] = np.add.reduceat(own.mixed(flat ^ np.uint64(0x5851F42D4C957F2D)), starts)
                    digests[1, full] = np.add.reduceat(own.mixed(flat + np.uint64(0x14057B7EF767814F)), starts)
                counts = np.bincount(row * BUCKETS + (flat & np.uint64(BUCKETS - 1)).astype(np.int64), minlength=len(sets) * BUCKETS)
                counts = np.minimum(counts, FULL).astype(np.uint8).reshape(len(sets), BUCKETS)
                heads = [head(h, len(h) - -(-len(h) * num // den) + 1) if len(h) else h for h in sets]
                ends = np.concatenate(([0], np.cumsum([len(h) for h in heads])))
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(heads).view(np.int64)))
                columns = [batch.column("id"), pa.array(size), *(pa.array(d.view(np.int64)) for d in digests), lists, pa.array([c.tobytes() for c in counts], pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, names=["id", "n_shingles", "d1", "d2", "head", "histogram"])

    return docs.mapInArrow(sign, "id bigint, n_shingles bigint, d1 bigint, d2 bigint, head array<bigint>, histogram binary")


def components(links: DataFrame) -> DataFrame:
    """``v, c``: each end of the links ``a, b`` and the least vertex that it is connected with.

    Labels shrink along links and then jump to the label of their label, until
    nothing changes.  Each round is a table in the shared folder.
    """
    both = written(links.select("a", "b").union(links.select("b", "a")).distinct(), "links")
    labels = written(both.groupBy(F.col("a").alias("v")).agg(F.least(F.col("a"), F.min("b")).alias("c")), "labels")
    while True:
        near = both.join(labels, both.b == labels.v).groupBy("a").agg(F.min("c").alias("m"))
        step = written(labels.join(near, labels.v == near.a).select("v", F.col("c").alias("old"), F.least("c", "m").alias("c")), "labels")
        up = step.select(F.col("v").alias("c"), F.col("c").alias("up"))
        new = written(step.join(up, "c").select("v", "old", F.least("c", "up").alias("c")), "labels")
        done = new.where("c <> old").isEmpty()
        discard(step)
        discard(labels)
        labels = new
        if done:
            discard(both)
            return held(labels.select("v", "c"), labels)


def _bounded(pairs: DataFrame, rows: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs ``a, b`` whose histograms leave room for the overlap that their sizes ask for."""
    sides = pairs
    for x in ("a", "b"):
        sides = sides.join(rows.select(F.col("rep").alias(x), F.col("n_shingles").alias(f"n_{x}"), F.col("histogram").alias(f"h_{x}")), x)

    def compare(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            n = batch.column("n_a").to_numpy() + batch.column("n_b").to_numpy()
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, BUCKETS) for c in ("h_a", "h_b"))
            low = np.minimum(x, y)
            most = np.where((low == FULL).any(axis=1), n, low.sum(axis=1, dtype=np.int64))
            yield batch.select(["a", "b"]).filter(pa.array(most * (num + den) >= num * n))

    return sides.select("a", "b", "n_a", "n_b", "h_a", "h_b").mapInArrow(compare, "a bigint, b bigint")


def _overlapping(pairs: DataFrame, docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """The pairs ``a, b`` whose full overlap reaches the threshold."""
    sides = pairs.join(docs.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")
    sides = sides.join(docs.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b").select("a", "b", "text_a", "text_b")

    def count(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        own = Hasher(n)
        for whole in batches:
            for batch in (whole.slice(k, TEXTS) for k in range(0, whole.num_rows, TEXTS)):
                left, right = (own.shingles(batch.column(c).to_pylist()) for c in ("text_a", "text_b"))
                same = np.array([len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(left, right, strict=True)], np.int64)
                n_both = np.array([len(x) + len(y) for x, y in zip(left, right, strict=True)], np.int64)
                yield batch.select(["a", "b"]).filter(pa.array(same * (num + den) >= num * n_both))

    return sides.mapInArrow(count, "a bigint, b bigint").distinct()


def _possible(x: str, y: str, num: int, den: int) -> Column:
    """Whether the sizes of two rows, and their places of a shared shingle, leave room for a link."""
    n, m, i, j = (F.col(f"{s}.{c}") for c in ("n", "pos") for s in (x, y))
    fits = den * F.least(n, m) >= num * F.greatest(n, m)
    return fits & (F.least(n - i, m - j) >= _needed(n, m, num, den))


def link_classes(docs: DataFrame, n: int = SHINGLE, threshold: tuple[int, int] = THRESHOLD, complete: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Signatures, classes with their components, and the links found between representatives.

    ``docs`` has ``id`` and ``text``.  The links span each component; pairs
    known to be connected already are not tested, unless ``complete`` asks for
    every link between different classes.
    """
    with _small_batches(docs.sparkSession):
        return _link_classes(docs, n, *threshold, complete)


@contextlib.contextmanager
def _small_batches(spark: SparkSession) -> Iterator[None]:
    """Fewer rows than usual go to a worker at a time, as some hold two texts."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    usual = spark.conf.get(key)
    spark.conf.set(key, str(ROWS))
    try:
        yield
    finally:
        spark.conf.set(key, usual)


def _link_classes(docs: DataFrame, n: int, num: int, den: int, complete: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    signed = written(signatures(docs, n, num, den), "signatures")
    full = signed.where((F.col("n_shingles") > 0) & F.col("id").isNotNull())
    classes = written(full.groupBy("d1", "d2", "n_shingles").agg(F.min("id").alias("rep")), "classes")
    rows = full.join(classes.withColumnRenamed("rep", "id"), ["id", "d1", "d2", "n_shingles"], "left_semi").withColumnRenamed("id", "rep")
    entries = rows.select("rep", F.col("n_shingles").alias("n"), F.posexplode("head").alias("pos", "h"))
    sizes = entries.groupBy("h").agg(F.count(F.lit(1)).alias("size")).where("size >= 2")
    columns = written(entries.join(sizes, "h"), "columns")
    shapes = written(full.select(F.col("id").alias("rep"), "d1", "d2", "n_shingles", "histogram").join(classes, ["rep", "d1", "d2", "n_shingles"], "left_semi").join(columns.select("rep").distinct(), "rep", "left_semi").dropDuplicates(["rep"]), "shapes")

    found: list[DataFrame] = []
    tested: list[DataFrame] = []
    labels = None

    def labelled() -> DataFrame:
        if labels is None:
            return columns.withColumn("c", F.col("rep"))
        return columns.join(labels.withColumnRenamed("v", "rep").withColumnRenamed("c", "_c"), "rep", "left").withColumn("c", F.coalesce("_c", "rep")).drop("_c")

    def open_columns(now: DataFrame) -> DataFrame:
        """The columns that hold rows of different components."""
        return now.groupBy("h").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("h")

    def test(pairs: DataFrame) -> bool:
        nonlocal labels
        pairs = pairs.distinct()
        if tested:
            pairs = pairs.join(reduce(DataFrame.union, tested), ["a", "b"], "left_anti")
        tested.append(written(pairs, "pairs"))
        near = written(_bounded(tested[-1], shapes, num, den), "near")
        ends = near.select(F.explode(F.array("a", "b")).alias("id")).distinct()
        texts = written(docs.join(ends, "id", "left_semi"), "texts")
        links = written(_overlapping(near, texts, n, num, den), "links")
        discard(near)
        discard(texts)
        if links.isEmpty():
            return False
        found.append(links)
        grown = components(reduce(DataFrame.union, found))
        before, labels = labels, written(grown, "components")
        discard(before, grown)
        return True

    pair = [F.least("x.rep", "y.rep").alias("a"), F.greatest("x.rep", "y.rep").alias("b")]
    apart = (F.col("x.rep") != F.col("y.rep")) & (F.lit(complete) | (F.col("x.c") != F.col("y.c"))) & _possible("x", "y", num, den)
    for order in () if complete else (F.struct("pos", "rep", "n", "c"), F.struct(F.xxhash64("rep").alias("_"), "pos", "rep", "n", "c")):
        now = written(labelled(), "columns-now")
        first = written(now.groupBy("h").agg(F.min(order).alias("y"), F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("h", "y"), "first")
        more = test(now.alias("x").join(first, "h").where(apart).select(*pair))
        discard(now)
        discard(first)
        if not more:
            break
    now = written(labelled(), "columns-now")
    open_now = None if complete else written(open_columns(now), "open")
    still = now if open_now is None else now.join(open_now, "h")
    blocks = F.ceil(F.col("size") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("rep"), blocks).cast("int")
    every = F.explode(F.sequence(F.lit(0), blocks - 1))
    x = still.select("h", "rep", "n", "pos", "c", own.alias("i"), every.alias("j"))
    y = still.select("h", "rep", "n", "pos", "c", every.alias("i"), own.alias("j"))
    test(x.alias("x").join(y.alias("y"), ["h", "i", "j"]).where(apart & (F.col("x.rep") < F.col("y.rep"))).select(*pair))
    discard(now, open_now, shapes, columns, *tested)
    empty = docs.sparkSession.range(0).select(F.col("id").alias("a"), F.col("id").alias("b"))
    links = held(reduce(DataFrame.union, found), *found) if found else empty
    joined = classes.withColumn("c", F.col("rep")) if labels is None else classes.join(labels.withColumnRenamed("v", "rep"), "rep", "left")
    named = written(joined.select("d1", "d2", "n_shingles", "rep", F.coalesce("c", "rep").alias("component_id")), "classes")
    discard(classes, labels)
    return signed, named, links


def linked_components(docs: DataFrame, n: int = SHINGLE, threshold: tuple[int, int] = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_shingles, class_id, component_id`` for each row of ``docs``.

    ``class_id`` is the least id with the same set of shingles, ``component_id`` the
    least id reachable by links.  A text without words (or a null one) has 0
    shingles and is alone; a row without id has null for both.
    """
    require(docs, [id_col, text_col])
    plain = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    signed, classes, links = link_classes(plain, n, threshold)
    discard(links)
    out = signed.drop("head", "histogram").join(classes, ["d1", "d2", "n_shingles"], "left")
    alone = (F.col("n_shingles") == 0) | F.col("id").isNull()
    own = lambda c: F.when(alone, F.col("id")).otherwise(F.col(c))
    return held(out.select(F.col("id").alias(id_col), "n_shingles", own("rep").alias("class_id"), own("component_id").alias("component_id")), signed, classes)


def link_counts(docs: DataFrame, n: int = SHINGLE, threshold: tuple[int, int] = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_shingles, class_id, component_id, n_links`` for each row of ``docs``.

    As :func:`linked_components`, with the number of other rows that a row links with.  All
    pairs of classes that pass the bounds are tested, those of one component too:
    a group of near copies costs the square of its different texts.
    """
    require(docs, [id_col, text_col])
    plain = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    signed, classes, links = link_classes(plain, n, threshold, complete=True)
    key = ["d1", "d2", "n_shingles"]
    sizes = written(signed.where("n_shingles > 0 AND id IS NOT NULL").groupBy(key).agg(F.count(F.lit(1)).alias("size")).join(classes, key).select(*key, "rep", "component_id", "size"), "sizes")
    both = links.select("a", "b").union(links.select("b", "a"))
    linked = both.join(sizes.select(F.col("rep").alias("b"), "size"), "b").groupBy(F.col("a").alias("rep")).agg(F.sum("size").alias("others"))
    counted = sizes.join(linked, "rep", "left").withColumn("n_links", F.col("size") - 1 + F.coalesce("others", F.lit(0)))
    out = signed.drop("head", "histogram").join(counted, key, "left")
    alone = (F.col("n_shingles") == 0) | F.col("id").isNull()
    own = lambda c, other: F.when(alone, other).otherwise(F.col(c))
    made = out.select(F.col("id").alias(id_col), "n_shingles", own("rep", F.col("id")).alias("class_id"), own("component_id", F.col("id")).alias("component_id"), own("n_links", F.lit(0)).alias("n_links"))
    return held(made, signed, classes, links, sizes)


def keep_one(docs: DataFrame, n: int = SHINGLE, threshold: tuple[int, int] = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component: that of the least id.  Rows without words or id stay."""
    groups = linked_components(docs, n, threshold, id_col, text_col)
    lost = groups.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias("lost"))
    rows = packed(docs)
    return held(unpacked(rows.join(lost, F.col(f"row.{id_col}") == F.col("lost"), "left_anti"), docs.columns, {}), groups)

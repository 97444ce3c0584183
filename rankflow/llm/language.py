"""Language identification by hyperdimensional profiles.

Every character has a random vector of -1 and 1.  A run of three is bound into
one: the product of its characters' vectors, each rotated by its place.  A text
is the sum of its runs, a language the sum of its texts, and a text is taken for
the language whose sum has the largest cosine with its own.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankflow.llm.common import require, with_fields

DIMENSIONS = 1024
GRAM = 3
#: Texts learned from, for each language, in expectation.
SAMPLE_PER_LANGUAGE = 1000
#: Bound vectors that a worker keeps; a full memory is emptied.
MEMORY = 20_000
SCALE = 1 << 24
UNDETERMINED = "und"


class Space:
    """The vectors of characters and of runs of three."""

    def __init__(self, dimensions: int = DIMENSIONS, seed: int = 20_240):
        import numpy as np

        self.np, self.d, self.seed = np, dimensions, seed
        self.letters: dict[int, object] = {}
        self.rows: dict[int, int] = {}
        self.table = np.empty((MEMORY, dimensions), np.float32)
        self.is_letter = np.zeros(0x110000, bool)
        self.known = np.zeros(0x110000, bool)

    def letter(self, c: int):
        found = self.letters.get(c)
        if found is None:
            random = self.np.random.Generator(self.np.random.Philox(key=[self.seed, c]))
            found = self.letters[c] = (random.integers(0, 2, self.d, self.np.int8) * 2 - 1).astype(self.np.int8)
        return found

    def codes(self, text: str):
        """Lower-cased letters as numbers, all else as single blanks; None if there is no letter."""
        np = self.np
        c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
        fresh = c[~self.known[c]]
        if len(fresh):
            for x in np.unique(fresh):
                self.known[x], self.is_letter[x] = True, chr(x).isalpha()
        letter = self.is_letter[c]
        if not letter.any():
            return None
        c = np.where(letter, c, 32).astype(np.int64)
        keep = np.ones(len(c), bool)
        keep[1:] = letter[1:] | letter[:-1]
        return np.concatenate(([32], c[keep], [32]))

    def vector(self, text: str):
        """The sum of the runs of a text; None for a text without letters."""
        np = self.np
        c = self.codes(text)
        if c is None:
            return None
        keys, counts = np.unique((c[:-2] << 42) | (c[1:-1] << 21) | c[2:], return_counts=True)
        total = np.zeros(self.d, np.float32)
        for k in range(0, len(keys), 4096):
            total += counts[k : k + 4096].astype(np.float32) @ self.bound(keys[k : k + 4096])
        return total

    def bound(self, keys):
        """The vectors of runs, a row each."""
        np = self.np
        names = keys.tolist()
        new = [k for k in names if k not in self.rows]
        if len(self.rows) + len(new) > MEMORY:
            self.rows.clear()
            new = names
        if new:
            at = len(self.rows)
            made = np.ones((len(new), self.d), np.int8)
            for place, shift in enumerate((42, 21, 0)):
                made *= np.stack([np.roll(self.letter(k >> shift & 0x1FFFFF), GRAM - 1 - place) for k in new])
            self.table[at : at + len(new)] = made
            self.rows.update(zip(new, range(at, at + len(new)), strict=True))
        return self.table[[self.rows[k] for k in names]]


def learn(docs: DataFrame, per_language: int = SAMPLE_PER_LANGUAGE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict[str, list[int]]:
    """Language to the sum of its sampled texts' unit vectors, as whole numbers.

    The sample is bounded: about ``per_language`` rows of each language, by a hash
    of the id.  Vectors are summed on the executors; what comes back, and is sent to
    the workers, is a number for each language and dimension (8 KB a language).
    """
    require(docs, [id_col, text_col, lang_col])
    docs = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    place = F.pmod(F.xxhash64("id"), F.lit(1 << 20))
    counts = docs.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    shares = counts.select(F.col("lang").alias("known"), F.greatest(F.lit(1), F.least(F.lit(1 << 20), F.floor(F.lit(per_language << 20) / F.col("n")))).alias("share"))
    # a row for each language, of which the profiles hold 8 KB each; so no text is moved
    sample = docs.join(F.broadcast(shares), F.col("lang") == F.col("known")).where(place < F.col("share")).select("lang", "text")

    def sums(batches: Iterator) -> Iterator:
        import pyarrow as pa

        space, total = Space(), {}
        for batch in batches:
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text"), strict=True):
                v = space.vector(text.as_py())
                if v is not None:
                    v = (v / space.np.linalg.norm(v) * SCALE).astype(space.np.int64)
                    total[lang] = total.get(lang, 0) + v
        yield pa.RecordBatch.from_pydict({"lang": pa.array(total, pa.string()), "v": pa.array([v.tolist() for v in total.values()], pa.list_(pa.int64()))})

    parts = sample.mapInArrow(sums, "lang string, v array<bigint>").select("lang", F.posexplode("v").alias("at", "x"))
    out: dict[str, list[int]] = {}
    for r in parts.groupBy("lang", "at").agg(F.sum("x").alias("x")).orderBy("lang", "at").collect():
        out.setdefault(r["lang"], []).append(r["x"])
    return out


def identify(docs: DataFrame, profiles: dict[str, list[int]], text_col: str = "text") -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, the cosine with that language, 0 to 1.

    ``und`` and 0 for a null text, a text without letters, or without any profile.
    Columns of these names in the input are replaced.
    """
    require(docs, [text_col])
    docs = docs.drop("lang_pred", "score")
    schema = with_fields(docs.schema).add("lang_pred", "string").add("score", "double")
    names = sorted(profiles)
    sums = [profiles[n] for n in names]

    def predict(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        space = Space()
        against = np.array(sums, np.float64).reshape(len(names), DIMENSIONS)
        against /= np.maximum(np.linalg.norm(against, axis=1, keepdims=True), 1e-12)
        for batch in batches:
            lang, score = [], []
            for text in batch.column(text_col):
                v = space.vector(text.as_py() or "") if names else None
                if v is None:
                    lang.append(UNDETERMINED)
                    score.append(0.0)
                    continue
                cosines = against @ v.astype(np.float64) / np.linalg.norm(v)
                best = int(cosines.argmax())
                lang.append(names[best])
                score.append(float(min(1.0, max(0.0, cosines[best]))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=schema.names)

    return docs.mapInArrow(predict, schema)

"""Toxicity by a weighted lexicon.

Texts are folded (lower case, look-alike letters and digits that stand for
letters) and matched by an Aho-Corasick automaton against terms that open a
word.  Phrases known to be harmless cover the terms inside them.  The weights of
what remains, as a sum and divided by the length, go through a logistic curve.
Terms, phrases, weights and curve are learned from labelled texts.
"""

from __future__ import annotations

import heapq
import math
import os
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.llm.common import require, with_fields

#: Letters that look like Latin ones, and signs and digits that stand for letters.
HOMOGLYPHS = dict(zip("аеорсухіјѕԁһӏьαορυιντкмтвнғ", "aeopcyxijsdhlbaopuivtkmtbhf", strict=True))
SUBSTITUTES = dict(zip("0134578@$!|", "oieastbasil", strict=True))
#: Labelled texts learned from, of each label at most, and their length in characters at most; longer ones are scored, but not learned from.
SAMPLE_PER_LABEL, SAMPLE_CHARS = 2000, 20_000
SHORTEST = 4
#: A term occurs in so many texts labelled 1, with such a log-odds weight, and such a weight of texts that others leave, or more.
LEAST_TEXTS, LEAST_WEIGHT, LEAST_GAIN = 3, 1.5, 12.0
THRESHOLD = 0.3

_FOLD = str.maketrans(HOMOGLYPHS)
_MIXED = re.compile(r"[\w@$!|]*(?:[^\W\d_][0134578@$!|]+|[0134578@$|]+[^\W\d_])[\w@$!|]*")
_DIGITS = str.maketrans(SUBSTITUTES)
_WORD = re.compile(r"[^\W\d_]+")


def fold(text: str) -> str:
    """Lower case, look-alikes as Latin letters; in words that mix both, digits and signs as letters."""
    text = text.lower()
    if not text.isascii():
        text = text.translate(_FOLD)
    return _MIXED.sub(lambda m: m[0].rstrip("!").translate(_DIGITS) + "!" * (len(m[0]) - len(m[0].rstrip("!"))), text)


@dataclass
class Lexicon:
    """Terms with weights, harmless phrases, and the curve's intercept and two slopes."""

    terms: dict[str, float] = field(default_factory=dict)
    exceptions: tuple[str, ...] = ()
    curve: tuple[float, float, float] = (-3.0, 0.0, 0.0)

    def automaton(self):
        import ahocorasick

        out = ahocorasick.Automaton()
        for t, w in self.terms.items():
            out.add_word(t, (len(t), w))
        for p in self.exceptions:
            out.add_word(p, (len(p), None))
        if len(out):
            out.make_automaton()
        return out

    def hits(self, folded: str, automaton) -> list[tuple[int, int, float]]:
        """Start, end and weight of the best term of each word, outside of exceptions."""
        if not len(automaton):
            return []
        best: dict[int, tuple[int, float]] = {}
        safe: list[tuple[int, int]] = []
        for last, (n, w) in automaton.iter(folded):
            start = last + 1 - n
            if start and folded[start - 1].isalnum():
                continue
            if w is None:
                if last + 1 == len(folded) or not folded[last + 1].isalnum():
                    safe.append((start, last + 1))
            elif start not in best or best[start][1] < w:
                best[start] = (last + 1, w)
        out, reach, k = [], -1, 0
        safe.sort()
        for s, (e, w) in sorted(best.items()):
            while k < len(safe) and safe[k][0] <= s:
                reach = max(reach, safe[k][1])
                k += 1
            if e > reach:
                out.append((s, e, w))
        return out

    def features(self, folded: str, automaton) -> tuple[float, float]:
        """Logarithm of the weight found, and that weight for each hundred words."""
        total = sum(w for *_, w in self.hits(folded, automaton))
        if not total:
            return 0.0, 0.0
        return math.log1p(total), math.log1p(100 * total / max(1, len(folded.split())))

    def score(self, text: str, automaton) -> float:
        a, b = self.features(fold(text), automaton)
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, self.curve[0] + self.curve[1] * a + self.curve[2] * b))))


def shared_openings(words: set[str]) -> set[str]:
    """The words, and the openings at which some of them part: of all openings of the same words the longest."""
    ordered = sorted(words)
    both = (os.path.commonprefix(pair) for pair in zip(ordered, ordered[1:], strict=False))
    return {p for p in (*ordered, *both) if len(p) >= SHORTEST}


def fit(rows: Iterable[tuple[str, int]], exceptions: tuple[str, ...] = ()) -> Lexicon:
    """A lexicon from texts and labels.

    Terms are word openings found in texts labelled 1 far more often than in
    others.  They are chosen so that each adds to what the others find, which keeps
    out words that merely stand beside them.  A phrase of a term and its neighbour
    that is found in harmless texts only is an exception.  Repeated rows count once.
    """
    import numpy as np

    rows = sorted({(fold(t or ""), int(y)) for t, y in rows})
    n = Counter(y for _, y in rows)
    if not n[0] or not n[1]:
        return Lexicon(exceptions=exceptions)
    words = {0: Counter(), 1: Counter()}
    pairs = {0: Counter(), 1: Counter()}
    texts = [(_WORD.findall(t), y) for t, y in rows]
    openings = shared_openings({x for w, y in texts if y for x in w})
    lengths = sorted(set(map(len, openings)))
    opened = lambda x, among: [x[:k] for k in lengths if k <= len(x) and x[:k] in among]
    for w, y in texts:
        words[y].update({p for x in set(w) for p in opened(x, openings)})
    weight = lambda t: math.log((words[1][t] + 0.5) / (n[1] + 1)) - math.log((words[0][t] + 0.5) / (n[0] + 1))
    usual = {t: w for t, k in words[1].items() if k >= LEAST_TEXTS and (w := weight(t)) >= LEAST_WEIGHT}
    found: dict[str, list[int]] = {t: [] for t in usual}
    for i, (w, y) in enumerate(texts):
        if y:
            for t in {p for x in set(w) for p in opened(x, usual)}:
                found[t].append(i)
    # Terms are taken one by one; a text counts half as much each time that a term of it is taken.
    counts = np.ones(len(texts))
    at = {t: np.array(i) for t, i in found.items()}
    gain = lambda t: usual[t] * float(counts[at[t]].sum())
    queue = [(-gain(t), -len(t), t) for t in usual]
    heapq.heapify(queue)
    terms: dict[str, float] = {}
    while queue:
        _, size, t = heapq.heappop(queue)
        now = gain(t)
        if now < LEAST_GAIN or any(terms[p] >= usual[t] - 0.1 for p in opened(t, terms) if p != t):
            continue
        if queue and now < -queue[0][0]:
            heapq.heappush(queue, (-now, size, t))
            continue
        terms[t] = usual[t]
        counts[at[t]] /= 2
    for w, y in texts:
        pairs[y].update({f"{a} {b}" for a, b in zip(w, w[1:], strict=False) if opened(a, terms) or opened(b, terms)})
    learned = [p for p, k in pairs[0].items() if k >= 3 and not pairs[1][p]]
    out = Lexicon(terms, tuple(sorted({*exceptions, *learned})))
    auto = out.automaton()
    x = np.array([(1.0, *out.features(t, auto)) for t, _ in rows])
    y = np.array([y for _, y in rows], float)
    beta = np.zeros(3)
    weights = np.where(y == 1, 0.5 / n[1], 0.5 / n[0]) * len(y)
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        h = (x * (weights * p * (1 - p))[:, None]).T @ x + 0.05 * np.eye(3)
        beta += np.clip(np.linalg.solve(h, x.T @ (weights * (y - p)) - 0.05 * beta), -5, 5)
    out.curve = tuple(float(b) for b in beta)
    return out


def learn(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_PER_LABEL, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Lexicon:
    """Fit on at most ``per_label`` labelled texts of each label, of at most ``SAMPLE_CHARS`` characters, the first by a hash of the id."""
    require(docs, [id_col, text_col])
    require(labels, [id_col, label_col])
    known = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(label_col).alias("y"))
    place = lambda *more: F.row_number().over(Window.partitionBy("y").orderBy(F.xxhash64("id"), "id", *more))
    chosen = known.withColumn("place", place()).where(F.col("place") <= per_label).select("id", "y")
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).join(F.broadcast(chosen), "id").where((F.char_length("t") <= SAMPLE_CHARS) | F.col("t").isNull())
    # ids may repeat in either table
    rows = texts.withColumn("place", place("t")).where(F.col("place") <= per_label).collect()
    return fit([(r["t"], r["y"]) for r in sorted(rows, key=lambda r: (r["id"], r["y"], r["t"] or ""))])


def score_documents(docs: DataFrame, lexicon: Lexicon, text_col: str = "text") -> DataFrame:
    """``docs`` with ``score``, 0 to 1; null and empty texts get the score of a text without a term.

    A column ``score`` of the input is replaced.
    """
    require(docs, [text_col])
    docs = docs.drop("score")
    schema = with_fields(docs.schema).add("score", "double")

    def rate(batches: Iterator) -> Iterator:
        import pyarrow as pa

        automaton = lexicon.automaton()
        for batch in batches:
            made = [lexicon.score(t.as_py() or "", automaton) for t in batch.column(text_col)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, pa.float64())], names=schema.names)

    return docs.mapInArrow(rate, schema)

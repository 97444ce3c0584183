"""The native operators against plain Python."""

import hashlib
import math
import random
import re
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from rankflow.llm import fingerprint, line_dedup, mixing, pii, quality

BLANK = " \t\n\x0b\x0c\r"
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words string, key string, line string"


def frame(spark, rows):
    """Rows ``(id, text)`` or ``(id, text, source)``, with columns whose names clash with inner ones."""
    return spark.createDataFrame([(r[0], r[1], "en", r[2] if len(r) > 2 else "s", 1, "x", "y", "z") for r in rows], SCHEMA)


def split(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


EDGE = [(1, None), (2, ""), (3, " \n\t "), (4, "a"), (5, "a b"), (6, "a b c d e"), (7, "é\x0bÀ # $"), (8, "a b\na b\n\nc"), (8, "a b\na b\n\nc"), (None, "no id here")]


def texts(k=60, seed=4):
    random.seed(seed)
    out = list(EDGE)
    for i in range(k):
        n = random.choice([3, 20, 60, 300])
        out.append((100 + i, "".join(random.choice(["the ", "of ", "Az ", "é", "x#", "\n", "\t", "b ", f"w{random.randint(0, 40)} "]) for _ in range(n))))
    out.append((999, "the long one " * 20_000))
    return out


def test_quality(spark):
    rows = texts()
    got = quality.quality_report(frame(spark, rows).select("doc_id", "text")).collect()
    assert len(got) == len(rows)
    by = defaultdict(list)
    for r in got:
        by[r["doc_id"], r["text"]].append(r)
    for i, t in rows:
        w = split(t)
        windows = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        count = Counter(windows)
        covered = {k + d for k, x in enumerate(windows) if count[x] > 1 for d in range(3)}
        lines = [x for x in (t or "").split("\n") if x.strip(BLANK)]
        want = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(covered))
        r = by[i, t][0]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
        assert not (r["kept"] and r["base_failed"])


def test_quality_keeps_columns_and_empty_tables(spark):
    docs = frame(spark, [(1, "the house of the rising sun is in the town " + " ".join(f"and word{i}" for i in range(40))), (2, "x")])
    kept = quality.keep_quality(docs)
    assert kept.columns == docs.columns
    assert [r["doc_id"] for r in kept.collect()] == [1]
    assert quality.keep_quality(docs.limit(0)).count() == 0


def kept_lines(rows, least=5, size=40):
    def key(line):
        return re.sub("[A-Z]", lambda m: m[0].lower(), line.strip(BLANK))

    holders = defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            if i is not None and len(key(x)) >= size:
                holders[key(x)].add(i)
    shared = {k: max(v) for k, v in holders.items() if len(v) >= least}
    return [(i, "\n".join(x for x in (t or "").split("\n") if i is None or shared.get(key(x), i) == i)) for i, t in rows]


def test_line_dedup(spark):
    random.seed(1)
    pool = [f"Shared LINE number {k} with enough letters to count É" for k in range(12)]
    rows = list(EDGE)
    for i in range(80):
        lines = random.choices([*pool, "short", "", f"own line of document {i} that nobody else has at all"], k=random.randint(0, 9))
        rows.append((100 + i, "\n".join(random.choice([x, "  " + x.upper().replace("É", "É") + "\t"]) for x in lines)))
    rows.append((500, "\n".join(pool * 300)))
    got = line_dedup.dedup_lines(frame(spark, rows)).collect()
    assert Counter((r["doc_id"], r["text"]) for r in got) == Counter(kept_lines(rows))
    first = {i: (t or "").count("\n") + 1 for i, t in rows}
    assert all(r["n_lines"] == first[r["doc_id"]] and r["n_lines"] - r["n_dropped"] == (r["text"].count("\n") + 1 if r["text"] or r["n_dropped"] < r["n_lines"] else 0) for r in got)
    assert line_dedup.dedup_lines(frame(spark, rows).limit(0)).count() == 0


def test_pfair_schedule_is_never_a_block_off():
    for parts in ({"a": 1, "b": 1}, {"a": 7, "b": 2, "c": 1}, {"a": 333, "b": 333, "c": 334}, {f"s{k}": k + 1 for k in range(20)}):
        q, done = sum(parts.values()), Counter()
        order, starts = mixing.schedule(parts, {s: float(n) for s, n in parts.items()})
        for t, s in enumerate(order, 1):
            done[s] += 1
            assert all(abs(done[x] - t * a / q) < 1 for x, a in parts.items()) or starts[1:] and t > starts[1]
        assert done == parts


def test_shares_are_exact():
    from fractions import Fraction

    for w in ({"a": 1.0}, {"a": 1e-9, "b": 1.0}, {f"s{k}": k + 0.5 for k in range(9)}, {"a": 1 / 3, "b": 2 / 3}):
        got = mixing.shares(w)
        assert all(Fraction(got[a], got[b]) == Fraction(w[a]) / Fraction(w[b]) for a in w for b in w)


def test_mix_places_every_row_once(spark):
    rows = [(i, "t", random.Random(i).choice(["a", "a", "a", "b", "c", None])) for i in range(700)] + [(3, "t", "a"), (None, "t", "b")]
    got = mixing.mix(frame(spark, rows), {"a": 1.0, "b": 2.0, "c": 1.0}, block=8).collect()
    assert sorted(r["mix_position"] for r in got) == list(range(len(rows)))
    at = sorted(got, key=lambda r: r["mix_position"])
    size = Counter(r[2] for r in rows)
    slots, per = defaultdict(set), Counter()
    for r in at:
        slots[r["mix_slot"]].add(r["source"])
        per[r["mix_slot"]] += 1
    assert all(len(s) == 1 for s in slots.values()) and max(per.values()) == 8
    assert sorted(slots) == list(range(len(slots)))
    done, target = Counter(), {"a": 0.25, "b": 0.5, "c": 0.25}
    for t in range(min(size["b"] // 8, 2 * (size["c"] // 8))):
        done[next(iter(slots[t]))] += 1
        assert all(abs(done[s] - (t + 1) * w) < 1 for s, w in target.items())
    assert all(at[k]["source"] is None for k in range(len(at) - size[None], len(at)))  # without a target: last
    assert mixing.mix(frame(spark, rows).limit(0)).count() == 0


def test_mixed_files_are_in_order(spark, tmp_path):
    docs = frame(spark, [(i, "t", f"s{i % 7}") for i in range(900)])
    mixing.in_order(mixing.mix(docs, block=16), 5).select("doc_id", "mix_position").write.parquet(str(tmp_path / "out"))
    files = sorted((tmp_path / "out").glob("part-*.parquet"))
    rows = [r["mix_position"] for f in files for r in spark.read.parquet(str(f)).collect()]
    assert rows == list(range(900)) and len(files) == 5


def jaccard(a, b, n=5):
    def sets(t):
        w = split(t)
        return {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()

    a, b = sets(a), sets(b)
    return len(a & b) / len(a | b) if a | b else 1.0


def test_fingerprints_follow_similarity(spark):
    random.seed(2)
    pairs = []
    for k in range(120):
        a = [f"w{random.randint(0, 10**6)}" for _ in range(random.choice([40, 200, 900]))]
        b = list(a)
        for _ in range(int(len(b) * random.choice([0, 0.01, 0.05, 0.2, 1]))):
            b[random.randrange(len(b))] = "x" + str(random.random())
        pairs.append((k, " ".join(a), " ".join(b)))
    df = spark.createDataFrame(pairs, "k int, a string, b string")
    got = df.select("k", "a", "b", fingerprint.likeness(fingerprint.fingerprint(F.col("a")), fingerprint.fingerprint(F.col("b"))).alias("s")).collect()
    errors = [r["s"] - jaccard(r["a"], r["b"]) for r in got]
    assert max(map(abs, errors)) < 0.17 and abs(sum(errors) / len(errors)) < 0.02
    assert all(r["s"] == 1.0 for r in got if r["a"] == r["b"])


def test_densified_bins_of_short_texts(spark):
    rows = [(1, ""), (2, "one"), (3, "one"), (4, "a b c d e"), (5, "a b c d e f"), (6, None)]
    got = {r["doc_id"]: r["fingerprint"] for r in fingerprint.fingerprint_documents(frame(spark, rows)).collect()}
    assert got[1] == got[6] == "" and got[2] == got[3] and len(got[2]) == 256 and "-" not in got[5]


@pytest.mark.parametrize("ids", [list(range(50)), [5], [0, 10**15, -(10**12), 7, 8, 9], [i * 1_000_003 for i in range(600)], list(range(1000, 1300)) + [2**62]])
def test_next_row_by_descending_id(spark, ids):
    rows = [(i, f"text {i}") for i in ids]
    random.Random(1).shuffle(rows)
    got = {r["doc_id"]: r["next_text"] for r in fingerprint.with_next(frame(spark, rows), ["text"]).collect()}
    down = sorted(ids, reverse=True)
    assert got == {i: f"text {down[(k + 1) % len(down)]}" for k, i in enumerate(down)}


def test_compare_with_next(spark):
    rows = [(i, t) for i, t in texts(20) if i is not None and i != 8]
    got = {r["doc_id"]: r for r in fingerprint.compare_with_next(frame(spark, rows)).collect()}
    down = sorted(rows, reverse=True, key=lambda r: r[0])
    for k, (i, t) in enumerate(down):
        t, after = t or "", down[(k + 1) % len(down)][1] or ""
        cut = len(t) // 3
        edited = t[: len(t) - cut] + after[:cut]
        assert got[i]["n_chars"] == len(t)
        assert got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert 0 <= got[i]["near_edited"] <= 1 and 0 <= got[i]["near_next"] <= 1
    assert fingerprint.compare_with_next(frame(spark, rows).limit(0)).count() == 0
    assert fingerprint.compare_with_next(frame(spark, [(None, "a"), (1, "b")])).count() == 2


PRIVATE = {
    "email": "jane.doe42@mail.example.com", "card": "4111 1111 1111 1111", "ip": "192.168.7.42", "phone": "+1 (988) 555-2485", "ssn": "123-45-6789",
    "iban": "DE89 3704 0044 0532 0130 00", "date": "1984-02-29",
}


def test_pseudonyms_keep_the_format_and_come_back(spark):
    key = "k1"
    rows = [(k, f"Contact: {v}, and again {v}.") for k, v in enumerate(PRIVATE.values())] + [(50, None), (51, ""), (52, "card 4111111111111112 and 2023-02-30 stay"), (53, "born 31.12.1999 or 12/31/1999 or 1999-12-31")]
    docs = frame(spark, rows)
    out = pii.pseudonymise(docs, key)
    got = {r["doc_id"]: r for r in out.collect()}
    shape = lambda s: re.sub("[A-Z]", "A", re.sub("[a-z]", "a", re.sub("[0-9]", "9", s)))
    for k, (kind, v) in enumerate(PRIVATE.items()):
        made = re.fullmatch(r"Contact: (.*), and again (.*)\.", got[k]["text"])
        assert made[1] == made[2] != v and got[k]["pii_kinds"] == [kind, kind]
        assert kind == "ip" or shape(made[1]) == shape(v)
    digits = [int(c) for c in got[1]["text"].split(":")[1].split(",")[0] if c.isdigit()]
    assert sum(x if k % 2 == 0 else sum(divmod(2 * x, 10)) for k, x in enumerate(reversed(digits))) % 10 == 0
    assert got[50]["text"] is None and got[51]["text"] == "" and got[52]["text"] == rows[9][1]
    a, b, c = re.findall(r"[\d./-]{10}", got[53]["text"])
    assert c == f"{a[6:]}-{a[3:5]}-{a[:2]}" == f"{b[6:]}-{b[:2]}-{b[3:5]}" != "1999-12-31"
    back = {r["doc_id"]: r["text"] for r in pii.reveal(out, key).collect()}
    assert back == {i: t for i, t in rows}
    assert pii.pseudonymise(docs, "k2").where("doc_id = 0").first()["text"] != got[0]["text"]
    assert pii.pseudonymise(docs.limit(0), key).count() == 0


def test_pseudonyms_are_a_permutation(spark):
    ids = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit("10.0."), F.floor(F.col("id") / 256), F.lit("."), F.col("id") % 256).alias("text"))
    assert pii.pseudonymise(ids, "k").select("text").distinct().count() == 3000
    days = spark.range(4000).select(F.col("id").alias("doc_id"), F.date_add(F.lit("1990-01-01").cast("date"), F.col("id").cast("int")).cast("string").alias("text"))
    made = pii.pseudonymise(days, "k")
    assert made.select("text").distinct().count() == 4000
    assert made.where(F.col("text").try_cast("date").isNull()).count() == 0
    assert math.isclose(made.where("text < '2000-01-01'").count() / 4000, 0.5, abs_tol=0.1)

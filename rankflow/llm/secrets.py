"""Secret scans: base patterns, and a linear-chain conditional random field beside them.

A text is cut into tokens, words and signs alike; the tokens of a line are a
chain, and each is tagged as secret begin, inside or outside.  What a tag is worth
adds up from the token's shape, the words and signs around it (by themselves and
with its class of shape), features of the file, and the tag before.  The field is trained
on short windows of a bounded sample: base matches with their keywords and with
other names in their place, secrets of many shapes planted into plain text, and
look-alikes that aren't secrets.

Chains are decoded by Viterbi.  A line is only decoded if a secret that begins at some
token of it could gain over O throughout, at the most that tags beside it add; in all other lines O
throughout is the best path.  That bound is taken for all tokens of a text at
once, from tables of the tokens seen.
"""

from __future__ import annotations

import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankflow.llm.common import require, with_fields

#: Fixed patterns; the match of a kind counts if the group named here is long enough.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
#: One of these is in each of its matches, in small letters.
STEMS = (b"passw", b"secret", b"token", b"api")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "crf")

TOKEN = re.compile(r"[^\W_]+(?:[-+/_.&$!@][^\W_]+)*={0,2}|[^\w\s]|_+|\n")
PART = re.compile(r"[^\W\d_]+")
#: Windows around a base match, and others, that the field is trained on at most; texts among which they are looked for; characters on each side.
SAMPLE, CANDIDATES, REACH = 300, 40_000, 150
#: Distinct tokens that a worker keeps, and tokens of a text that it takes at a time.
MEMORY, SLICE = 1 << 18, 1 << 14
O, B, I = range(3)
#: Context: the name of a place and how far back it is; those before the token and the one after it.
PLACES = {"before1": 1, "before2": 2, "before3": 3, "before4": 4, "after": -1}
CLASSES = 6
#: The feature of a token that is one of the two before it.
AGAIN = "again"
SPANS = "array<struct<kind:string,start:int,end:int>>"


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Matches of the base patterns, by start and then kind; positions in code points."""
    small = text.encode("utf-8", "surrogatepass").lower()  # A-Z alone, as in the pattern
    out = [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6] if any(k in small for k in STEMS) else []
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    out += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    return sorted(out, key=lambda x: (x[1], KINDS.index(x[0])))


def _bucket(x: float, *edges: float) -> int:
    return sum(x >= e for e in edges)


def file_features(size: int, signs: int) -> list[str]:
    """What the text as a whole looks like, by its characters and how many of them code has."""
    return [f"file-signs {_bucket(signs / max(1, size), 0.002, 0.01, 0.05)}", f"file-size {_bucket(size, 200, 2000, 20000)}"]


def _signs(text: str) -> int:
    return sum(map(text.count, '={;"'))


def shape_class(s: str) -> int:
    """Sign, small word, other word, digits with signs, letters with digits, letters with signs."""
    if s.isalpha():
        return 1 if s.islower() else 2
    digits, letters = any(map(str.isdigit, s)), any(map(str.isalpha, s))
    if not digits and not letters:
        return 0
    if not digits:
        return 5
    return 4 if letters else 3


def own_features(s: str) -> list[str]:
    """The shape of a token; of a short word, no more than length and letters."""
    n = len(s)
    size, title = f"length {_bucket(n, 3, 5, 8, 12, 16, 20, 24, 32, 40)}", f"title {s.istitle()}"
    if n < 12 and s.isalpha():
        kinds = "".join(("" if s.islower() else "u", "" if s.isupper() else "l", "" if s.isascii() else "n"))
        return ["bias", f"kinds {kinds}", size, f"{kinds} {size}", title]
    digits, upper, lower, letters = (sum(map(f, s)) for f in (str.isdigit, str.isupper, str.islower, str.isalpha))
    kinds = "".join(("d" if digits else "", "u" if upper else "", "l" if lower else "", "s" if digits + letters < n else "", "" if s.isascii() else "n"))
    out = ["bias", f"kinds {kinds}", size, f"{kinds} {size}", title, f"digits {_bucket(digits / n, 0.1, 0.25, 0.5, 0.75, 1)}", f"at {'@' in s}", f"dots {min(3, s.count('.'))}"]
    if n >= 12:
        turns = sum((a.isdigit(), a.isupper()) != (b.isdigit(), b.isupper()) for a, b in zip(s, s[1:], strict=False))
        spread = -sum(k / n * math.log2(k / n) for k in map(s.count, set(s)))
        out += [f"turns {_bucket(turns / n, 0.1, 0.25, 0.4)}", f"spread {_bucket(spread, 2.5, 3, 3.5, 4)}", f"hex {not s.strip('0123456789abcdefABCDEF-')}"]
    return out


def parts(s: str) -> set[str]:
    """The words of a neighbour, in small letters; a sign or number stands for itself or its kind."""
    if s.isalpha():
        return {s.lower()}
    return set(PART.findall(s.lower())) or {"0" if s[:1].isdigit() else s[:2]}


def context_features(place: str, cls: int, s: str) -> list[str]:
    return [f for p in parts(s) for f in (f"{place} {p}", f"{place} {cls} {p}")]


def token_features(tokens: list[str], t: int, about: list[str]) -> list[str]:
    """All features of a token in its place; text begins and ends with line breaks."""
    cls = shape_class(tokens[t])
    out = own_features(tokens[t]) + about
    for place, back in PLACES.items():
        k = t - back
        out += context_features(place, cls, tokens[k] if 0 <= k < len(tokens) else "\n")
    return out + [AGAIN] * any(t >= k and tokens[t - k] == tokens[t] for k in (1, 2))


@dataclass
class Field:
    """Weights of the three tags by feature, and of neighbouring tags; O stands around each chain."""

    weights: dict[str, tuple[float, float, float]] = field(default_factory=dict)
    moves: list[list[float]] = field(default_factory=lambda: [[0.0] * 3 for _ in range(3)])

    def turns(self) -> list[list[float]]:
        out = [list(map(float, row)) for row in self.moves]
        out[O][I] = -1e9
        return out

    def decode(self, scores: list[list[float]]) -> list[int]:
        """The best tags of a chain, given what each tag is worth at each token; by Viterbi."""
        (oo, ob, _), (bo, bb, bi), (io, ib, ii) = self.turns()  # no chain goes from outside to inside
        s = scores[0]
        o, b, i, back = s[O] + oo, s[B] + ob, s[I] - 1e9, []
        for x in scores[1:]:
            to_o, to_b = o + oo, o + ob
            via_o = via_b = O
            if b + bo > to_o:
                to_o, via_o = b + bo, B
            if i + io > to_o:
                to_o, via_o = i + io, I
            if b + bb > to_b:
                to_b, via_b = b + bb, B
            if i + ib > to_b:
                to_b, via_b = i + ib, I
            to_i, via_i = (b + bi, B) if b + bi >= i + ii else (i + ii, I)
            back.append((via_o, via_b, via_i))
            o, b, i = to_o + x[O], to_b + x[B], to_i + x[I]
        ends = (o + oo, b + bo, i + io)
        tags = [ends.index(max(ends))]
        for came in reversed(back):
            tags.append(came[tags[-1]])
        return tags[::-1]


class Scorer:
    """A field applied to whole texts, with tables of the tokens seen."""

    def __init__(self, own: Field):
        import numpy as np

        self.np, self.field = np, own
        m = own.turns()
        #: The most that the tags before it can add to a token that is tagged B or I, and the end of a secret to its path.
        self.lift = [max(m[a][y] for a in range(3)) - m[O][O] for y in (B, I)]
        self.leave = max(0.0, max(m[B][O], m[I][O]) - m[O][O])
        #: What a part of a neighbour is worth, by place and class.
        self.parts: dict[str, object] = {}
        places = {p: k for k, p in enumerate(PLACES)}
        for name, w in own.weights.items():
            place, _, rest = name.partition(" ")
            if place in places:
                cls, _, part = rest.rpartition(" ")
                at = self.parts.setdefault(part, np.zeros((len(PLACES), CLASSES, 3)))
                at[places[place], int(cls) if cls else slice(None)] += w
        self.plain: dict[tuple, object] = {}
        self.again = self._worth([AGAIN])
        self.clear()

    def clear(self) -> None:
        np = self.np
        self.rows: dict[str, int] = {}
        #: What tokens are worth by themselves, and where that of each is: short words of one shape share it.
        self.own = np.zeros((MEMORY + 1, 3))
        self.mine = np.zeros(MEMORY + 1, np.int32)
        self.shapes: dict[tuple, int] = {}
        self.owned = 0
        self.cls = np.zeros(MEMORY + 1, np.int8)
        self.near = np.zeros(MEMORY + 1, np.int32)
        self.table = np.zeros((256, len(PLACES), CLASSES, 3))
        self.filled = 1
        self.around: dict[tuple[str, ...], int] = {(): 0}

    def _worth(self, names: list[str]):
        found = [w for w in map(self.field.weights.get, names) if w is not None]
        return self.np.sum(found, axis=0) if found else self.np.zeros(3)

    def _own(self, s: str):
        if len(s) < 12 and s.isalpha():
            key = (len(s), s.islower(), s.isupper(), s.istitle(), s.isascii())
            if key not in self.plain:
                self.plain[key] = self._worth(own_features(s))
            return self.plain[key]
        return self._worth(own_features(s))

    def _near(self, known: tuple[str, ...]) -> int:
        """Where the worth of a neighbour with these known parts is: neighbours with the same share a row."""
        k = self.around.get(known)
        if k is None:
            if self.filled == len(self.table):
                self.table = self.np.concatenate((self.table, self.np.zeros_like(self.table)))
            k = self.around[known] = self.filled
            self.table[k] = sum(map(self.parts.get, known))
            self.filled += 1
        return k

    def take(self, some: list[str]) -> None:
        """Put tokens into the tables that aren't there."""
        rows, known, plain = self.rows, self.parts, self.shapes
        first, mine, cls, near = len(rows), [], [], []
        for s in some:
            if s in rows:
                continue
            rows[s] = len(rows)
            if len(s) < 12 and s.isalpha():
                lower = s.islower()
                key = (len(s), lower, s.isascii()) if lower else (len(s), s.isupper(), s.istitle(), s.isascii())
                k = plain.get(key)
                if k is None:
                    k = plain[key] = self.owned
                    self.own[k] = self._own(s)
                    self.owned += 1
                part = s.lower()
                mine.append(k)
                cls.append(1 if lower else 2)
                near.append(self._near((part,)) if part in known else 0)
            else:
                self.own[self.owned] = self._own(s)
                mine.append(self.owned)
                self.owned += 1
                cls.append(shape_class(s))
                near.append(self._near(tuple(sorted(p for p in parts(s) if p in known))))
        at = slice(first, len(rows))
        self.mine[at], self.cls[at], self.near[at] = mine, cls, near

    def scores(self, tokens: list[str], about: list[str]):
        """What each tag is worth at each token, a row each."""
        np = self.np
        out, file = np.empty((len(tokens), 3)), self._worth(about)
        back, ahead = max(PLACES.values()), -min(PLACES.values())
        padded = ["\n"] * back + tokens + ["\n"] * ahead
        for at in range(0, len(tokens), SLICE):
            some = padded[at : at + SLICE + back + ahead]
            if len(self.rows) + len(some) > MEMORY:
                self.clear()
            get = self.rows.get
            ids = np.array([get(s, -1) for s in some], np.int32)
            new = np.flatnonzero(ids < 0).tolist()
            if new:
                self.take([some[k] for k in new])
                ids[new] = [self.rows[some[k]] for k in new]
            n = len(some) - back - ahead
            again = (ids[back : back + n] == ids[back - 1 : back - 1 + n]) | (ids[back : back + n] == ids[back - 2 : back - 2 + n])
            if at == 0:  # nothing is before the first token
                again[0] = False
                again[1:2] = ids[back + 1 : back + n][:1] == ids[back]
            mine, near = ids[back : back + n], self.near[ids]
            cls, total = self.cls[mine], self.own[self.mine[mine]] + file
            for k, steps in enumerate(PLACES.values()):
                total += self.table[near[back - steps : back - steps + n], k, cls]
            total[again] += self.again
            out[at : at + n] = total
        return out

    def bound(self, scores, tokens: list[str]):
        """The most that a path can gain over O throughout by a secret that begins at each token, within its line."""
        np = self.np
        inside = scores[:, I] - scores[:, O] + self.lift[1]
        inside[[k for k, s in enumerate(tokens) if s == "\n"]] = -1e4
        total = np.cumsum(inside)
        best = np.maximum.accumulate(total[::-1])[::-1]
        return scores[:, B] - scores[:, O] + self.lift[0] + best - total + self.leave

    def spans(self, text: str) -> list[tuple[str, int, int]]:
        """Base spans and what the field adds, by start and then kind."""
        base = base_spans(text)
        tokens = TOKEN.findall(text)
        if not tokens or not self.field.weights:
            return base
        np, out = self.np, list(base)
        scores = self.scores(tokens, file_features(len(text), _signs(text)))
        hopeful = np.flatnonzero(self.bound(scores, tokens) > 0)
        if not len(hopeful):
            return base
        breaks = np.array([-1, *(k for k, s in enumerate(tokens) if s == "\n"), len(tokens)])
        places = [m.span() for m in TOKEN.finditer(text)]
        for line in np.unique(np.searchsorted(breaks, hopeful)):
            first, stop = breaks[line - 1] + 1, breaks[line]
            if first >= stop:
                continue
            tags = self.field.decode(scores[first:stop].tolist())
            k = 0
            while k < len(tags):
                if tags[k] != B:
                    k += 1
                    continue
                end = k + 1
                while end < len(tags) and tags[end] == I:
                    end += 1
                start, last = places[first + k][0], places[first + end - 1][1]
                out.append(("crf", start, last))
                k = end
        return sorted(_apart(base, out[len(base) :]) + base, key=lambda x: (x[1], KINDS.index(x[0])))


def _apart(base: list[tuple[str, int, int]], more: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Those of ``more`` that overlap none of ``base``; both by start.  One pass over each."""
    out, k, reach = [], 0, -1
    ordered = sorted(base, key=lambda x: x[1])
    for kind, start, end in more:
        while k < len(ordered) and ordered[k][1] < end:
            reach = max(reach, ordered[k][2])
            k += 1
        if reach <= start:
            out.append((kind, start, end))
    return out


#: What secrets are called, and what stands between the name and the secret: fixed values.
NAMES = "password, passphrase, pass phrase, passcode, pass code, pwd, credential, credentials, login, client secret, client_secret_key, secret key, api key, access key, access token, auth token, auth_token, bearer, private key, signing key, encryption key, db_pass, pin code, key, code, token, session id, licence key, backup code, recovery phrase".split(", ")
LINKS = (": ", " = ", "=", " -> ", ': "', ' = "', " := ", " is ", " was set to ", " ")
LETTERS, SMALL, CAPITALS, DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
PREFIXES = ("sk_live_", "ghp_", "pk-", "xoxb-", "AIza", "glpat-", "SG.")
#: What follows the name of a secret, or looks like one, and is none.
HARMLESS = (
    "the password is required for all of them", "a token of thanks", "the secret of the house", "key: see below", "password reset", "the code is short", "access key holders", "secret: none", "token ring",
    "the key point is that it works", "login page", "pin the paper to the wall", "the pass over the hill is closed", "session notes", "backup of the files", "the recovery phrase is kept in the safe",
)


def a_secret(draw: random.Random, words: list[str]) -> tuple[str, bool]:
    """A made-up secret of some shape, and whether it shows without a name."""
    some = lambda among, n: "".join(draw.choices(among, k=n))
    kind = draw.randrange(10)
    if kind < 2:
        return some(LETTERS + DIGITS, draw.randint(20, 40)), True
    if kind == 2:
        return some(LETTERS + DIGITS + "+/", draw.randint(22, 42)) + draw.choice(["", "=", "=="]), True
    if kind == 3:
        return draw.choice(PREFIXES) + some(LETTERS + DIGITS, draw.randint(16, 36)), True
    if kind == 4:
        return "-".join(some(CAPITALS + DIGITS, 5) for _ in range(draw.randint(3, 5))), True
    if kind == 5:
        return "-".join(some("0123456789abcdef", n) for n in (8, 4, 4, 4, 12)), False
    if kind == 6:
        return " ".join(some(LETTERS + DIGITS, 4) for _ in range(draw.randint(3, 6))), False
    if kind == 7 and len(words) >= 6:
        return " ".join(draw.sample(words, draw.randint(4, 6))), False
    if kind == 8:
        return some(CAPITALS, 1) + some(SMALL, draw.randint(3, 6)) + some(DIGITS, draw.randint(2, 4)) + draw.choice("&$!@") + some(SMALL + DIGITS, draw.randint(1, 4)), False
    return some(SMALL + DIGITS, draw.randint(8, 20)), False


def a_decoy(draw: random.Random) -> str:
    """Something that isn't a secret, though it has digits or the name of one."""
    some = lambda among, n: "".join(draw.choices(among, k=n))
    number = lambda n: some(DIGITS, n)
    made = (
        lambda: f"order {number(4)}-{number(4)}", lambda: f"invoice INV-{number(4)}-{number(4)}", lambda: f"ISBN 978-3-{number(2)}-{number(6)}-0", lambda: f"+1 ({number(3)}) 555-{number(4)}",
        lambda: f"20{number(2)}-0{draw.randint(1, 9)}-1{number(1)} 12:{draw.randint(10, 59)}:05", lambda: f"version v{number(1)}.{number(2)}.3", lambda: f"www.example.com/{some(SMALL, 5)}/{some(SMALL, 6)}-{some(SMALL, 4)}/20{number(2)}",
        lambda: f"{some(SMALL, 6)}{number(2)}@mail{number(1)}.example.com", lambda: ".".join(str(draw.randint(0, 255)) for _ in range(4)), lambda: f"{some(CAPITALS, 2)}{number(2)} {number(4)} {number(4)} {number(4)} {number(2)}",
        lambda: f"{number(4)} {number(4)} {number(4)} {number(4)}", lambda: number(16), lambda: f"commit {some('0123456789abcdef', 7)}", lambda: f"{some(SMALL, 4)}_{some(SMALL, 5)}_0{number(1)}.txt", lambda: f"get{some(CAPITALS, 1)}{some(SMALL, 6)}ById{number(1)}",
        lambda: " ".join([some(SMALL, draw.randint(2, 7))] * draw.randint(4, 15)), lambda: f"code {number(3)}", lambda: f"room {some(CAPITALS, 1)}{number(3)}", lambda: f"{number(2)}th", lambda: f"key {number(1)}", lambda: draw.choice(HARMLESS), lambda: draw.choice(HARMLESS), lambda: draw.choice(HARMLESS),
    )
    return draw.choice(made)()


def planted(draw: random.Random, window: str, names: list[str] = NAMES) -> tuple[str, list[tuple[int, int]]]:
    """A window with a secret, a look-alike or both put between its words, and the secret's span."""
    words = [w for w in re.findall(r"[^\W\d_]+", window.lower()) if len(w) > 2]
    gaps = [m.start() for m in re.finditer(r"(?<=\S) (?=\S)", window)]
    at = draw.choice(gaps) if gaps else len(window)
    put, spans = " ", []
    if draw.random() < 0.5:
        put += a_decoy(draw) + draw.choice([" ", ". ", ", ", "\n"])
    if draw.random() < 0.75:
        secret, shows = a_secret(draw, words)
        if not shows or draw.random() < 0.75:
            name, link = draw.choice(names), draw.choice(LINKS[:7] if secret.islower() and " " in secret else LINKS)
            put += draw.choice([name, name.capitalize(), name.upper(), f"the {name}", f"my {name}", name.replace(" ", "_")]) + link
        else:
            link = ""
        spans.append((at + len(put), at + len(put) + len(secret)))
        put += secret + ('"' if '"' in link else "")
    return window[:at] + put + draw.choice(["", ".", ",", "\n"]) + window[at:], spans


def _renamed(draw: random.Random, window: str) -> tuple[str, list[tuple[int, int]]]:
    """A window with the keywords of its base matches replaced by other names."""
    out, spans, at = "", [], 0
    for m in ASSIGN.finditer(window):
        if len(m[2]) >= 6:
            out += window[at : m.start(1)] + draw.choice(NAMES) + window[m.end(1) : m.start(2)]
            spans.append((len(out), len(out) + len(m[2])))
            out += m[2]
            at = m.end(2)
    return out + window[at:], spans


def _tagged(text: str, secrets: list[tuple[int, int]], about: list[str]) -> Iterator[tuple[list[list[str]], list[int]]]:
    """The chains of a window, as features and tags."""
    found = [(m[0], *m.span()) for m in TOKEN.finditer(text)]
    tokens = [s for s, *_ in found]
    rows: list[list[str]] = []
    tags: list[int] = []
    last = None
    for t, (s, start, end) in enumerate(found):
        if s == "\n":
            if rows:
                yield rows, tags
            rows, tags, last = [], [], None
            continue
        own = next((x for x in secrets if x[0] < end and start < x[1]), None)
        rows.append(token_features(tokens, t, about))
        tags.append(O if own is None else I if own == last else B)
        last = own
    if rows:
        yield rows, tags


def _values(window: str) -> list[tuple[int, int]]:
    """Where the secrets themselves are in base matches."""
    out = [m.span(2) for m in ASSIGN.finditer(window) if len(m[2]) >= 6]
    return out + [(s, e) for k, s, e in base_spans(window) if k != "assign" and not any(a <= s < b for a, b in out)]


def fit(windows: list[tuple[str, int, int]], seed: int = 3) -> Field:
    """A field trained on windows ``(text, characters of its document, signs of code there)``, in the order given."""
    draw, data = random.Random(seed), []
    for window, size, signs in windows:
        about = file_features(size, signs)
        data += _tagged(window, _values(window), about)
        if _values(window):
            data += _tagged(*_renamed(draw, window), about)
        else:
            for _ in range(2):
                data += _tagged(*planted(draw, window), about)
    return _trained(data)


def _trained(data: list[tuple[list[list[str]], list[int]]], rounds: int = 40, ridge: float = 0.1, least: int = 6) -> Field:
    """Climb the likelihood of all chains at once, by steps for each weight that grow while its gradient keeps its sign.

    Features seen with a secret fewer than ``least`` times are left out: the words of plain text.
    """
    import numpy as np

    if not data:
        return Field()
    data = sorted(data, key=lambda x: -len(x[1]))
    often = Counter(name for rows, tags in data for row, y in zip(rows, tags, strict=True) if y != O for name in row)
    index = {name: k for k, name in enumerate(n for n, seen in often.items() if seen >= least)}
    lengths = np.array([len(tags) for _, tags in data])
    start = np.cumsum(lengths) - lengths
    rows = [[index[name] for name in row if name in index] for rows, _ in data for row in rows]
    feats, owner = np.array([f for row in rows for f in row]), np.repeat(np.arange(len(rows)), list(map(len, rows)))
    tags = np.concatenate([t for _, t in data])
    truth = np.eye(3)[tags]
    before, first = np.concatenate(([O], tags[:-1])), np.zeros(len(tags), bool)
    first[start] = True
    before[first] = O
    last = start + lengths - 1
    seen = np.zeros((3, 3))
    np.add.at(seen, (before, tags), 1)
    np.add.at(seen, (tags[last], O), 1)
    running = np.searchsorted(-lengths, -np.arange(lengths[0]), side="left")  # chains with a token at each step, longest first
    inner = np.flatnonzero(~first)
    value = np.zeros((len(index) + 3, 3))  # weights, and below them the moves
    step, past = np.full_like(value, 0.1), np.zeros_like(value)
    summed = lambda x, axis: np.log(np.exp(x - (top := x.max(axis=axis, keepdims=True))).sum(axis=axis)) + top.squeeze(axis)
    for _ in range(rounds):
        weights, moves = value[:-3], value[-3:]
        scores = np.stack([np.bincount(owner, weights=weights[feats, y], minlength=len(tags)) for y in range(3)], axis=1)
        m = moves.copy()
        m[O, I] = -1e9
        ahead, behind = np.empty_like(scores), np.empty_like(scores)
        ahead[start] = scores[start] + m[O]
        for t in range(1, len(running)):
            at = start[: running[t]] + t
            ahead[at] = scores[at] + summed(ahead[at - 1][:, :, None] + m, 1)
        behind[last] = m[:, O]
        for t in range(len(running) - 2, -1, -1):
            at = start[: running[t + 1]] + t
            behind[at] = summed(m + (scores[at + 1] + behind[at + 1])[:, None, :], 2)
        total = summed(ahead[start] + behind[start], 1)
        each = np.repeat(total, lengths)
        off = truth - np.exp(ahead + behind - each[:, None])
        grow = np.stack([np.bincount(feats, weights=off[owner, y], minlength=len(index)) for y in range(3)], axis=1)
        pairs = np.exp(ahead[inner - 1][:, :, None] + m + (scores[inner] + behind[inner])[:, None, :] - each[inner][:, None, None]).sum(0)
        pairs[O] += np.exp(ahead[start] + behind[start] - total[:, None]).sum(0)
        pairs[:, O] += np.exp(ahead[last] + behind[last] - total[:, None]).sum(0)
        slope = np.concatenate((grow, seen - pairs)) - ridge * value
        step = np.where(slope * past > 0, np.minimum(1.2 * step, 1.0), np.where(slope * past < 0, 0.5 * step, step))
        past = np.where(slope * past < 0, 0.0, slope)
        value = value + np.sign(past) * step
    return Field({name: tuple(map(float, value[k])) for name, k in index.items()}, value[-3:].tolist())


def sampled(docs: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``y, h, window, size, signs``: at most ``sample`` windows with a base match and as many others, in one pass over the texts.

    They are the first by a hash of the id among about ``CANDIDATES`` texts, chosen by another hash.
    """
    require(docs, [id_col, text_col])
    share = min(1 << 30, (CANDIDATES << 30) // max(1, docs.count()) + 1)
    text, key = F.coalesce(F.col(text_col), F.lit("")), F.col(id_col)
    hit = r"(?:[pP][aA][sS][sS][wW](?:[oO][rR])?[dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])[\"']? *[:=] *[\"']?[A-Za-z0-9+/_.=-]{6}|AKIA[A-Z0-9]{16}|[0-9a-f]{24}"
    some = docs.where(key.isNotNull() & (F.pmod(F.xxhash64(key, F.lit(5)), F.lit(1 << 30)) < share)).select(F.xxhash64(key).alias("h"), text.alias("t"), F.regexp_instr(text, F.lit(hit)).alias("at"))
    size = F.char_length("t")
    start = F.when(F.col("at") > 0, F.greatest(F.col("at") - REACH, F.lit(1))).otherwise(F.pmod(F.col("h"), F.greatest(size - 2 * REACH, F.lit(1))).cast("int") + 1)
    signs = F.octet_length("t") - F.octet_length(F.regexp_replace("t", '[={;"]', ""))
    cut = some.select((F.col("at") > 0).alias("y"), "h", F.substring("t", start, F.lit(2 * REACH)).alias("window"), size.cast("long").alias("size"), signs.cast("long").alias("signs"))
    place = F.row_number().over(Window.partitionBy("y").orderBy("h", "window", "size"))
    return cut.withColumn("place", place).where(F.col("place") <= sample).drop("place")


def learn(docs: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> Field:
    """A field trained on the windows of :func:`sampled`; of nothing, one that tags nothing."""
    rows = sampled(docs, sample, id_col, text_col).collect()
    return fit([(r["window"], r["size"], r["signs"]) for r in sorted(rows, key=lambda r: (r["y"], r["h"], r["window"], r["size"]))])


def find_secrets(docs: DataFrame, field: Field, text_col: str = "text") -> DataFrame:
    """``docs`` with ``secret_spans``: kind, start and end (exclusive) in code points, by start and kind.

    Base spans are all there; the field adds spans of kind ``crf`` that overlap none
    of them.  A null text counts as empty.  Replaces a column of that name.
    """
    require(docs, [text_col])
    docs = docs.drop("secret_spans")
    schema = with_fields(docs.schema).add("secret_spans", docs.sparkSession.range(0).select(F.lit(None).cast(SPANS).alias("x")).schema["x"].dataType)

    def scan(batches: Iterator) -> Iterator:
        import pyarrow as pa

        own = Scorer(field)
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        for batch in batches:
            made = [[dict(zip(("kind", "start", "end"), x, strict=True)) for x in own.spans(t.as_py() or "")] for t in batch.column(text_col)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, kind)], names=schema.names)

    return docs.mapInArrow(scan, schema)


def listed(some: Column) -> Column:
    """Spans as ``kind:start:end``, comma-joined."""
    return F.array_join(F.transform(some, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")

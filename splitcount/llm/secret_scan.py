"""Secret scanning: fixed patterns, then a guess-cost test of values in a credential context.

The patterns find assignments, access keys and long hex strings.  Beyond them, values that follow a
wider set of credential words, or that stand as the password of a URL, are judged by the number of
guesses a password cracker would need: a dynamic programme cuts the value into dictionary words,
dates, repeats, keyboard walks, sequences and brute-force spans at the least total cost (in log10
guesses).  Words are a short list of common passwords and then the corpus's own words by frequency, so
that prose after a credential word is weak whatever its language.  Values at or above ``min_guesses`` become
spans of kind ``guess``; spans of the patterns always stay.

Offsets are code points, ends exclusive.  Defined results: a null text is the empty text and has no
span; texts of any length are scanned whole, the programme being linear in the value's length and keeping
one number per character; costs of 10^16 guesses and more count as that.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from collections.abc import Iterable, Iterator
from math import log10

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut

# The three base patterns.  ASCII matching keeps "either case" to A-Z and a-z.
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
_HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
_KINDS = ("assign", "access", "hex", "guess")

# Further words that announce a credential, and the password part of a URL.
_CONTEXT = re.compile(
    r"""(?:password|passwd|passphrase|pwd|secret|token|api_?key|credential|private_?key|access_?key|auth|bearer)["']?\x20*(?:[:=]|\bis\b)\x20*(["']?)([^\x20\x09-\x0D"'<>,;|]{6,})""",
    re.IGNORECASE | re.ASCII,
)
_URL = re.compile(r"[a-z][a-z0-9+.-]{1,15}://[^\x20\x09-\x0D/@:]{1,64}:([^\x20\x09-\x0D/@]{6,})@", re.IGNORECASE | re.ASCII)

# Common passwords and password words, most common first.
COMMON_WORDS = """123456 password qwerty admin welcome letmein login monkey dragon master hello freedom
whatever trustno1 iloveyou princess football baseball shadow sunshine superman batman secret default
changeme guest root test user demo example sample temp public private access system server database
backup summer winter spring autumn monday friday january december love money house happy flower ginger
cookie pepper charlie jordan michael jennifer thomas hunter ranger soccer hockey killer george andrew
joshua matthew daniel ashley computer internet service account network office company manager support
security key token pass word code the and for you that with this from have not are was one all new your
apple orange banana cheese coffee purple yellow silver golden diamond star angel tiger lion eagle
""".split()
_NEVER = float("inf")
# Letters that digits and signs stand for.
_LEET = str.maketrans({"4": "a", "@": "a", "3": "e", "1": "i", "!": "i", "0": "o", "5": "s", "$": "s", "7": "t", "+": "t"})
# Keyboard rows.
_ROWS = ("`1234567890-=", "qwertyuiop[]\\", "asdfghjkl;'", "zxcvbnm,./")
_DATE = re.compile(r"(?:19|20)\d\d(?:[-/.]?(?:0[1-9]|1[0-2])[-/.]?(?:0[1-9]|[12]\d|3[01]))?|(?:0[1-9]|[12]\d|3[01])[-/.]?(?:0[1-9]|1[0-2])[-/.]?(?:19|20)?\d\d")


_KEY_AT = {ch: (x, y) for y, row in enumerate(_ROWS) for x, ch in enumerate(row)}
_TWO = log10(2)
#: Costs of this and more are reported as this; such a value is strong under any threshold below it.
ENOUGH = 16.0
#: Log10 guesses for the length of a run: powers of two, and one cost for 64 and more.
_FAR = 64
_LENGTH = [0.0] + [_TWO * (n.bit_length() - 1) for n in range(1, _FAR + 1)]


def _move(a: str, b: str) -> tuple[int, int] | None:
    """Step between neighbouring keys, or None."""
    if a == b or a not in _KEY_AT or b not in _KEY_AT:
        return None
    (x, y), (u, v) = _KEY_AT[a], _KEY_AT[b]
    return (u - x, v - y) if abs(u - x) <= 1 and abs(v - y) <= 1 else None


def _alphabet(ch: str) -> float:
    if ch.isdigit():
        return 1.0
    if ch.isascii() and ch.isalpha():
        return log10(26)
    return log10(33) if ch.isascii() else 2.0


class _Run:
    """The starts of a run that still goes on, one unit apart, with what a segment from there costs besides its length.

    Lengths between two powers of two cost the same, so an end compares one minimum for each power; of the starts
    ``_FAR`` units back and more, whose lengths cost the same, the least is kept.
    """

    def __init__(self, unit: int = 1):
        self.unit, self.first, self.costs, self.far = unit, 0, [], _NEVER

    def clear(self) -> None:
        if self.costs:
            self.costs, self.far = [], _NEVER

    def start(self, at: int, cost: float) -> None:
        if not self.costs:
            self.first = at
        self.costs.append(cost)

    def least(self) -> float:
        return min(self.far, min(self.costs, default=_NEVER))

    def end(self, at: int, units: int) -> float:
        """Least cost of a segment that ends here and has so many units or more."""
        costs = self.costs
        if not costs:
            return _NEVER
        longest = (at - self.first) // self.unit
        if longest >= _FAR:
            self.far = min(self.far, costs.pop(0))
            self.first += self.unit
            longest -= 1
        best, low = self.far + _LENGTH[_FAR], units
        while low <= longest:  # lengths low..high cost the same
            high = min(2 ** low.bit_length() - 1, longest)
            best = min(best, min(costs[longest - high : longest - low + 1]) + _LENGTH[low])
            low = high + 1
        return best


class Guesser:
    """Least log10 guesses of values, with the built-in words ranked first and then the given ones."""

    def __init__(self, words: Iterable[str] = ()):
        self.ranks = {w: k + 1 for k, w in enumerate(dict.fromkeys([*COMMON_WORDS, *words]))}
        self.longest = max(map(len, self.ranks))
        self.known: dict[str, float] = {}

    def cost(self, value: str) -> float:
        if len(value) > 64:
            return self._search(value)
        got = self.known.get(value)
        if got is None:
            if len(self.known) >= 20_000:  # a bounded memory of short values
                self.known.clear()
            got = self.known[value] = self._search(value)
        return got

    def word(self, raw: str, low: str, plain: str) -> float:
        """Cost of a dictionary word, also with capitals or with signs for letters."""
        rank, extra = self.ranks.get(low), 0.0
        if rank is None:
            rank, extra = self.ranks.get(plain), 2 * _TWO
        if rank is None:
            return _NEVER
        return log10(rank + 1) + extra + (0.0 if raw == low else _TWO if raw.isupper() or raw.istitle() else 3 * _TWO)

    def _search(self, value: str) -> float:
        """Least sum over all segmentations, at most ``ENOUGH``.

        Every segment after the first costs a factor of two, as a cracker must also try where to cut.  ``brute`` is the
        least cost that ends inside a brute-force span, which may go on without a new cut; ``after[i]`` is the least
        cost of anything before a segment that starts at i.  Runs offer every start and every end; blocks are offered
        at every period that costs less than ``ENOUGH``.
        """
        n = len(value)
        low = value.lower()
        if len(low) != n:
            low = value
        plain = low.translate(_LEET)
        after, brute = array("d", [0.0]), _NEVER
        equal, steps, walk = _Run(), _Run(), _Run()
        blocks = {p: [_Run(p) for _ in range(p)] for p in range(2, min(n // 2, int(ENOUGH)) + 1)}
        turns, direction, step, free = 0.0, None, 0, _NEVER
        reach = max(self.longest, 10)  # words and dates
        lately = max(reach, int(ENOUGH)) + 2
        for j in range(1, n + 1):
            ch = low[j - 1]
            free = _NEVER
            if j > 1:
                i, last = j - 2, low[j - 2]
                if ch == last:
                    equal.start(i, after[i] + _alphabet(value[i]))
                    free = min(free, equal.end(j, 3))
                else:
                    equal.clear()
                up = ord(ch) - ord(last)
                if up != step:
                    steps.clear()
                    step = up
                if abs(up) == 1:
                    steps.start(i, after[i] + _alphabet(value[i]) + _TWO)
                    free = min(free, steps.end(j, 3))
                move = _move(last, ch)
                if move is None:
                    walk.clear()
                    turns = 0.0
                else:
                    if direction is not None and move != direction:
                        turns += _TWO
                    walk.start(i, after[i] + log10(47) - turns)  # pays the turns after its own first step
                    free = min(free, walk.end(j, 4) + turns)
                direction = move
            for p, runs in blocks.items():
                i = j - 1 - p
                if i >= 0 and low[i] == ch:
                    runs[i % p].start(i, after[i] + sum(map(_alphabet, value[i : i + p])))
                    free = min(free, runs[j % p].end(j, 2))
                elif i >= 0:
                    for r in runs:
                        r.clear()
            for i in range(max(0, j - reach), j - 2):
                if after[i] < free:
                    free = min(free, after[i] + self.word(value[i:j], low[i:j], plain[i:j]))
                    if ch.isdigit() and 4 <= j - i <= 10 and (m := _DATE.fullmatch(value, i, j)):
                        free = min(free, after[i] + log10(200 if m.end() - i == 4 else 366 * 200))
            brute = _alphabet(value[j - 1]) + min(brute, after[j - 1])
            after.append(min(free, brute) + _TWO)
            if j % 32 == 0 and min(brute, *after[-lately:], walk.least() + turns) >= ENOUGH and all(r.least() >= ENOUGH for r in (equal, steps, *(x for y in blocks.values() for x in y))):
                return ENOUGH  # whatever follows, no cut or span so far leads to less
        return min(free, brute, ENOUGH) if n else 0.0


def corpus_words(docs: DataFrame, text_col: str = "text", max_words: int = 20_000) -> list[str]:
    """The most frequent words of all whole texts, most frequent first, ties in alphabetical order.

    Only words between white space and punctuation count, and nothing that follows a colon or an equals sign, so
    that a credential repeated in many copies is no word.  At most 100,000 words can hold a share of 1/100,000, so
    what is sorted and what reaches the driver is bounded whatever the corpus.
    """
    prose = F.regexp_replace(F.coalesce(F.col(text_col), F.lit("")), r"[:=]\x20*[\"']?[^\x20\x09-\x0D]+", " ")
    found = F.regexp_extract_all(prose, F.lit(r"(?<![^\x20\x09-\x0D(])(\p{L}{3,24})(?=[\x20\x09-\x0D.,;!?)]|$)"), F.lit(1))
    counts = cut(docs.select(F.explode(found).alias("w")).groupBy(F.lower("w").alias("w")).agg(F.count("*").alias("n")))
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    often = counts.where(F.col("n") * 100_000 >= total)
    return [r["w"] for r in often.orderBy(F.desc("n"), "w").limit(max_words).collect()]


def base_spans(text: str) -> list[tuple[int, int, int, int, int]]:
    """(start, kind number, end, value start, value end) of the three patterns."""
    out = [(m.start(), 0, m.end(), m.start(2), m.end(2)) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    out += [(m.start(), 1, m.end(), m.start(), m.end()) for m in _ACCESS.finditer(text)]
    out += [(m.start(), 2, m.end(), m.start(), m.end()) for m in _HEX.finditer(text)]
    return out


def guess_spans(text: str, min_guesses: float, guesser: Guesser) -> list[tuple[int, int, int, int, int]]:
    """Values in a credential context that withstand 10 ** min_guesses guesses, one span per place."""
    found = {}
    for m, g in [*((m, 2) for m in _CONTEXT.finditer(text)), *((m, 1) for m in _URL.finditer(text))]:
        a, b = m.start(g), m.end(g)
        while b - a >= 6 and text[b - 1] in ".:!?)]}":
            b -= 1
        if b - a >= 6 and guesser.cost(text[a:b]) >= min_guesses:
            found.setdefault((a, b), (a, 3, b, a, b))
    return list(found.values())


def all_spans(text: str, min_guesses: float, guesser: Guesser) -> list[tuple[int, int, int, int, int]]:
    return sorted(set(base_spans(text)) | set(guess_spans(text, min_guesses, guesser)))


def joined(spans) -> str:
    return ",".join(f"{_KINDS[k]}:{a}:{b}" for a, k, b, *_ in sorted(spans))


_SCAN = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_guess long, weakest double"


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_guesses: float = 8.0, words: Iterable[str] | None = None) -> DataFrame:
    """Spans per row; ``weakest`` is the least log10 guesses among values of assignments, else null.

    ``words`` None: the corpus's own.
    """
    guesser = docs.sparkSession.sparkContext.broadcast(Guesser(corpus_words(docs, text_col) if words is None else words))  # at most max_words words

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = guesser.value
        for b in batches:
            rows = []
            for i, t in zip(b["i"].astype("Int64"), b["t"], strict=True):
                base = sorted(base_spans(t))
                spans = sorted(set(base) | set(guess_spans(t, min_guesses, g)))
                n = [sum(s[1] == k for s in spans) for k in range(4)]
                costs = [g.cost(t[s[3] : s[4]]) for s in base if s[1] == 0]
                rows.append((i, n[0], n[1], n[2], hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans), n[3], round(min(costs), 6) if costs else None))
            yield pd.DataFrame(rows, columns=_SCAN.replace(" long", "").replace(" string", "").replace(" double", "").split(", ")).astype({"doc_id": "Int64"})

    return docs.select(F.col(id_col).cast("long").alias("i"), F.coalesce(F.col(text_col), F.lit("")).alias("t")).mapInPandas(run, _SCAN)


def redact(text: str, guesser: Guesser, min_guesses: float = 8.0, mark: str = "<secret>") -> str:
    """The text with the value of every span replaced; overlapping spans become one mark."""
    out, at = [], 0
    for a, b in sorted((s[3], s[4]) for s in all_spans(text, min_guesses, guesser)):
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join(out) + text[at:] if out else text


def redacted(docs: DataFrame, text_col: str = "text", min_guesses: float = 8.0, words: Iterable[str] | None = None) -> Column:
    """Column expression over ``docs`` for :func:`redact`; null stays null."""
    guesser = docs.sparkSession.sparkContext.broadcast(Guesser(corpus_words(docs, text_col) if words is None else words))

    @F.pandas_udf("string")
    def run(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: None if t is None else redact(t, guesser.value, min_guesses))

    return run(F.col(text_col))


def op3_secret_scan(spark, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))

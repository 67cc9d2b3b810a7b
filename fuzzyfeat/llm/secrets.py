"""Secrets in texts: fixed patterns, and values in credential contexts by what guessing them would cost.

The cost of a value is the least over its segmentations into words, dates, repeats, keyboard walks and brute-force spans:
the sum of the decimal logarithms of the segments' guesses, found by dynamic programming over the value's positions. A value in a credential context that is no match of a fixed pattern becomes a span of kind
`guess` if it costs at least LEAST_COST digits, so `pwd=letmein` is left alone and `pwd=x9$Kq2!vRw` is not.

Null texts count as empty. Every text is read whole. Rows come back as often as they went in.
"""

from __future__ import annotations

import math
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.llm import _spans
from fuzzyfeat.session import materialise, prepare

KINDS = ("assign", "access", "hex")
LEAST_COST, LEARNED_WORDS = 8.0, 20_000
#: Fixed patterns.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
CONTEXT = re.compile(r"""(?:(?:pwd|pass|passphrase|pin|auth|authorization|bearer|credentials?|private_?key|access_?key|client_?secret|password|passwd|secret|token|api_?key)["']?(?:[ \t]*[:=][ \t]*|[ \t]+is[ \t]+)(?:(?:bearer|basic)[ \t]+)?["']?|://[^\s:/@]{1,64}:)([^\s"'@,;]{6,})""", re.I | re.A)
HINTS = ("password", "passwd", "secret", "token", "apikey", "api_key")
MORE_HINTS = ("pwd", "pass", "pin", "auth", "bearer", "credential", "key", "://")
#: Fixed list of words that guessers try first, most frequent first.
COMMON = "password 123456 qwerty letmein admin welcome monkey dragon master login princess sunshine football shadow baseball iloveyou abc123 trustno1 secret root test guest user demo example changeme default hello love summer winter spring autumn the and for you that with this from your have not are but all new time server system data key pass token access public private company office home house computer internet google apple orange banana money power world flower tiger lion eagle star super magic happy lucky blue green red black white gold silver january february march april may june july august september october november december monday friday sunday".split()
LEET = str.maketrans("4@3$501!7", "aaessoiit")
RANK = {w: i + 1 for i, w in reversed(list(enumerate(COMMON)))}
ROWS = ("`1234567890-=", "qwertyuiop[]\\", "asdfghjkl;'", "zxcvbnm,./")
PLACE = {c: (x + 0.5 * y, y) for y, row in enumerate(ROWS) for x, c in enumerate(row)}
DATE = re.compile(r"(?:19|20)\d\d(?:([-/._]?)(?:0[1-9]|1[0-2])\1(?:0[1-9]|[12]\d|3[01]))?|(?:0?[1-9]|[12]\d|3[01])([-/._])(?:0?[1-9]|1[0-2])\2(?:19|20)\d\d")
LONGEST_WORD, LONGEST_DATE = max(map(len, COMMON)), 10


def _adjacent(a: str, b: str) -> bool:
    p, q = PLACE.get(a.lower()), PLACE.get(b.lower())
    return bool(p and q and a.lower() != b.lower() and abs(p[0] - q[0]) <= 1 and abs(p[1] - q[1]) <= 1)


def _dates(value: str, i: int) -> Iterator[tuple[int, float]]:
    """Ends and costs of the dates that begin at i."""
    for j in range(i + 4, min(len(value), i + LONGEST_DATE) + 1):
        if DATE.fullmatch(value, i, j):
            yield j, math.log10(200 if j - i == 4 else 365 * 200)


def guess_cost(value: str, rank: dict[str, int] = RANK, longest: int = LONGEST_WORD) -> float:
    """Decimal logarithm of the guesses that the cheapest segmentation takes.

    Segments: a word of `rank`, a date, a repeat of a unit of one to four characters, a keyboard walk of four characters or
    more, or a single character by brute force. Every part of a longer repeat or walk is a segment, too.
    """
    n = len(value)
    alphabet = sum(size for size, test in ((26, str.islower), (26, str.isupper), (10, str.isdigit)) if any(map(test, value))) + 33 * any(not c.isalnum() for c in value)
    each = math.log10(max(10, alphabet))
    lowered = value.lower()
    if len(lowered) != n:
        lowered = value
    plain = lowered.translate(LEET)
    ends: list[list[tuple[int, float]]] = [[] for _ in range(n + 1)]  # of each end: (begin, cost)
    for i in range(n):
        for j in range(i + 2, min(n, i + longest) + 1):
            word = lowered[i:j]
            place = rank.get(word) or rank.get(plain[i:j])
            if place:
                ends[j].append((i, math.log10(place + 1) + 0.3 * (value[i:j] != word) + 0.3 * (word not in rank)))
        for j, c in _dates(value, i) if lowered[i].isdigit() else ():
            ends[j].append((i, c))
    cost = np.zeros(n + 1)
    begins = [0] * 5  # of each unit: where the run of that period that reaches here begins
    walk = 0
    for j in range(1, n + 1):
        best = min((cost[i] + c for i, c in ends[j]), default=math.inf)
        best = min(best, cost[j - 1] + each)
        for unit in range(1, 5):
            if j > unit and value[j - 1] != value[j - 1 - unit]:
                begins[unit] = j - unit
            last = j - max(3, 2 * unit)
            if last >= begins[unit]:
                i = np.arange(begins[unit], last + 1)
                best = min(best, float((cost[i] + np.log10(j - i)).min()) + each * unit)
        if j > 1 and not _adjacent(value[j - 2], value[j - 1]):
            walk = j - 1
        if j - walk >= 4:
            i = np.arange(walk, j - 3)
            best = min(best, float((cost[i] + 0.55 * (j - i - 1)).min()) + math.log10(47))
        cost[j] = best
    return float(cost[n])


def find(text: str, least_cost: float = LEAST_COST, cost_of: Callable[[str], float] = guess_cost) -> list[tuple]:
    """Spans (kind, start, end, base, score) by start, then kind. score: guess cost of the value, if it has one."""
    found: list[tuple] = []
    lowered = text.lower()
    hinted = any(h in lowered for h in HINTS)
    if hinted:
        found += [("assign", m.start(), m.end(), True, cost_of(m[2])) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [("access", m.start(), m.end(), True, None) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [("hex", m.start(), m.end(), True, None) for m in HEX.finditer(text)]
    if hinted or any(h in lowered for h in MORE_HINTS):
        taken = [(s[1], s[2]) for s in found]
        for m in CONTEXT.finditer(text):
            value = m[1].rstrip(".!?)")
            start, end = m.start(1), m.start(1) + len(value)
            if len(value) >= 6 and not any(a < end and start < b for a, b in taken):
                cost = cost_of(value)
                if cost >= least_cost:
                    found.append(("guess", start, end, False, cost))
    order = {k: i for i, k in enumerate((*KINDS, "guess"))}
    return sorted(found, key=lambda s: (s[1], order[s[0]]))


def frequent_words(docs: DataFrame, most: int = LEARNED_WORDS, text_col: str = "text") -> list[str]:
    """The `most` words of the documents by their number, counted over all of them; ties in order of the alphabet.

    Words that make up less than 1 / (20 most) of all can't be so many that the driver minds, and are left out before they get there.
    """
    words = docs.select(F.explode(F.regexp_extract_all(F.lower(F.col(text_col)), F.lit(r"(?<![a-z0-9])([a-z]{3,20})(?![a-z0-9])"), 1)).alias("word"))
    counts = materialise(words.groupBy("word").agg(F.count("*").alias("n")).filter("n > 1"))
    total = counts.agg(F.sum("n")).first()[0] or 0
    return [r["word"] for r in counts.filter(F.col("n") * (20 * most) >= total).orderBy(F.desc("n"), "word").limit(most).collect()]


def secret_spans(docs: DataFrame, least_cost: float = LEAST_COST, id_col: str = "doc_id", text_col: str = "text", learned_words: int = LEARNED_WORDS) -> DataFrame:
    """(doc_id, spans) of every row. Guessers are taken to know the fixed list of words, and after it the documents' most frequent ones."""
    spark = prepare(docs.sparkSession)
    known = [*COMMON, *(frequent_words(docs, learned_words, text_col) if learned_words else [])]
    shared = spark.sparkContext.broadcast({w: i + 1 for i, w in reversed(list(enumerate(known)))})

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = shared.value
        longest = max(map(len, rank))
        cost_of = lambda value: guess_cost(value, rank, longest)
        for batch in batches:
            for at in range(0, len(batch), 512):
                part = batch.slice(at, 512)
                yield _spans.batch(part.column(0), [find(x.as_py() or "", least_cost, cost_of) for x in part.column(1)])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col)).mapInArrow(work, f"doc_id long, spans {_spans.SPANS}")

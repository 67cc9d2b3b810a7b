"""Personal data in texts: fixed patterns, and a linear-chain conditional random field over word shapes.

The field is trained in numpy on a small labelled table (training_table) by gradient ascent on the conditional likelihood,
and decoded by an exact Viterbi pass over runs of documents: blocks of words advance in step for every entry label at once,
the blocks are then linked one after the other, and document bounds cut the chain. What it finds beside the fixed patterns
becomes spans of kinds crf_email, crf_ip, crf_card and crf_phone; the spans of the fixed patterns stay as they are.

Null texts count as empty. Every text is read whole. Rows come back as often as they went in.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fuzzyfeat.llm import _spans, _text
from fuzzyfeat.session import prepare

KINDS = ("email", "ip", "card", "phone")
LABELS = ("other", *KINDS)
BLOCK = 64
#: Fixed patterns.
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple]:
    """Matches of the fixed patterns, by kind, then start."""
    found: list[tuple] = []
    if "@" in text:
        found += [("email", m.start(), m.end(), True, None) for m in EMAIL.finditer(text)]
    if DIGIT.search(text):
        found += [("ip", m.start(), m.end(), True, None) for m in IP.finditer(text) if all(len(x.lstrip("0")) <= 3 and int(x[-4:]) <= 255 for x in m[0].split("."))]
        for m in CARD.finditer(text):
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and luhn(digits):
                found.append(("card", m.start(), m.end(), True, None))
        if "+" in text:
            found += [("phone", m.start(), m.end(), True, None) for m in PHONE.finditer(text) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]
    return found


def training_table(seed: int = 3, n: int = 400) -> list[list[tuple[str, str]]]:
    """Labelled sentences: (word, label) lists, made by rule from carrier sentences and formats of each kind."""
    g = np.random.default_rng(seed)
    digits = lambda k: "".join(map(str, g.integers(0, 10, k)))
    pick = lambda xs: xs[g.integers(len(xs))]
    names = "anna ben carla david erik fatima george hanna ivan julia".split()
    fill = "Please the order of note und der que la les pour mit call write send from to at in on is was about number contact office, Meeting tomorrow. Ends version item page chapter room".split()
    makers = {
        "email": [lambda: f"{pick(names)}.{pick(names)}@{pick(names)}.com", lambda: f"{pick(names)}{digits(2)}@mail.example.org,", lambda: f"<{pick(names)}@{pick(names)}.net>", lambda: f"{pick(names)} [at] {pick(names)} [dot] com", lambda: f"{pick(names)} (at) {pick(names)}.org"],
        "ip": [lambda: ".".join(str(g.integers(0, 256)) for _ in range(4)), lambda: ".".join(str(g.integers(0, 256)) for _ in range(4)) + ",", lambda: ".".join(str(g.integers(0, 256)) for _ in range(4)) + ":8080"],
        "card": [lambda: digits(16), lambda: " ".join(digits(4) for _ in range(4)), lambda: "-".join(digits(4) for _ in range(4)), lambda: f"{digits(4)} {digits(6)} {digits(5)}"],
        "phone": [lambda: f"+{g.integers(1, 99)} ({digits(3)}) {digits(3)}-{digits(4)}", lambda: f"+{g.integers(1, 99)} {digits(3)} {digits(7)}", lambda: f"({digits(3)}) {digits(3)}-{digits(4)}", lambda: f"{digits(3)}-{digits(3)}-{digits(4)}", lambda: f"0{digits(3)}/{digits(6)}"],
        "other": [lambda: digits(g.integers(1, 5)), lambda: f"{digits(2)}.{digits(2)}", lambda: f"{digits(4)}-{digits(2)}-{digits(2)}", lambda: f"v{digits(1)}.{digits(1)}.{digits(1)}", lambda: f"{digits(1)},{digits(3)}", lambda: f"@{pick(names)}", lambda: f"#{digits(3)}", lambda: f"{digits(2)}:{digits(2)}", lambda: f"${digits(2)}.{digits(2)}", lambda: f"a{digits(8)}f{digits(6)}", lambda: f"({pick(fill)})", lambda: "|", lambda: f"({digits(1)})"],
    }
    rows = []
    for _ in range(n):
        row: list[tuple[str, str]] = []
        for _ in range(g.integers(1, 4)):
            row += [(pick(fill), "other") for _ in range(g.integers(1, 6))]
            kind = pick(LABELS)
            row += [(w, kind) for w in pick(makers[kind])().split()]
        rows.append(row + [(pick(fill), "other") for _ in range(g.integers(1, 4))])
    return rows


_CLASS = np.zeros((9, 256), np.int32)
for _row, _chars in enumerate(("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "@", ".", "-/", "()[]<>", "+", ":")):
    _CLASS[_row, [ord(c) for c in _chars]] = 1


def shapes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Shape code of each word: buckets of its digits and other letters, and which marks it has."""
    if not len(starts):
        return np.zeros(0, np.int64)
    digit, lower, upper, at, dot, dash, bracket, plus, colon = np.add.reduceat(_CLASS[:, np.concatenate([data, [32]])], np.stack([starts, ends], 1).reshape(-1), axis=1)[:, ::2]
    digits = np.digitize(digit, [1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 16, 20])
    letters = np.digitize(lower + upper, [1, 2, 3, 5])
    code = digits * 5 + letters
    for mark, most in ((at, 1), (dot, 3), (dash, 2), (bracket, 1), (plus, 1), (colon, 1)):
        code = code * (most + 1) + np.minimum(mark, most)
    return code


N_SHAPES = 13 * 5 * 2 * 4 * 3 * 2 * 2 * 2


class Field:
    """Weights of the shapes of a word, of the word before and of the word after, and of label transitions."""

    def __init__(self) -> None:
        L = len(LABELS)
        self.own, self.before, self.after = (np.zeros((N_SHAPES, L), np.float32) for _ in range(3))
        self.step, self.first = np.zeros((L, L), np.float32), np.zeros(L, np.float32)

    def emissions(self, codes: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """begins: whether a word is the first of its document."""
        out = self.own[codes]
        if len(codes) > 1:
            out[1:] += self.before[codes[:-1]] * ~begins[1:, None]
            out[:-1] += self.after[codes[1:]] * ~begins[1:, None]
        return out

    def decode(self, emissions: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """The best labels of all words: exact Viterbi, block-parallel."""
        n, L = emissions.shape
        if not n:
            return np.zeros(0, np.int8)
        blocks = -(-n // BLOCK)
        pad = blocks * BLOCK - n
        e = np.concatenate([emissions, np.zeros((pad, L), np.float32)]).reshape(blocks, BLOCK, L)
        b = np.concatenate([begins, np.ones(pad, bool)]).reshape(blocks, BLOCK)
        score = np.where(np.eye(L, dtype=bool), np.float32(0), np.float32(-1e9))[None].repeat(blocks, 0)  # [block, entry label, label]
        back = np.empty((BLOCK, blocks, L, L), np.int8)
        for t in range(BLOCK):
            through = score[:, :, :, None] + np.where(b[:, t, None, None], self.first[None, None, :], self.step[None])[:, None]
            back[t] = through.argmax(axis=2)
            score = through.max(axis=2) + e[:, t, None, :]
        state, entered = np.zeros(L, np.float32), np.empty((blocks, L), np.int8)
        for i in range(blocks):
            total = state[:, None] + score[i]
            entered[i] = total.argmax(axis=0)
            state = total.max(axis=0)
            state = state - state.max()
        exit_, entry = np.empty(blocks, np.int8), np.empty(blocks, np.int8)
        last = int(state.argmax())
        for i in range(blocks - 1, -1, -1):
            exit_[i] = last
            last = entry[i] = entered[i, last]
        labels, now, rows = np.empty((blocks, BLOCK), np.int8), exit_.astype(np.int64), np.arange(blocks)
        for t in range(BLOCK - 1, -1, -1):
            labels[:, t] = now
            now = back[t, rows, entry, now].astype(np.int64)
        return labels.reshape(-1)[:n]


def fit(table: list[list[tuple[str, str]]], rounds: int = 60, rate: float = 0.5, decay: float = 1e-4) -> Field:
    """Gradient ascent on the conditional log-likelihood, by forward-backward over all rows in step."""
    model, L = Field(), len(LABELS)
    text = [" ".join(w for w, _ in row) for row in table]
    column = pa.array(text)
    _, _, data, offsets = next(_text.runs(column, 1 << 40))
    starts, ends, _ = _text.words(data, offsets)
    codes = shapes(data, starts, ends)
    begins = np.isin(starts, offsets[:-1])
    gold = np.array([LABELS.index(label) for row in table for _, label in row])
    bounds = np.flatnonzero(begins)
    length = np.diff(np.append(bounds, len(codes)))
    T, n = length.max(), len(length)
    index = np.minimum(bounds[:, None] + np.arange(T), len(codes) - 1)
    mask = np.arange(T) < length[:, None]
    inner = np.flatnonzero(~begins)
    squares = {k: np.full_like(getattr(model, k), 1e-8) for k in ("own", "before", "after", "step", "first")}
    for _ in range(rounds):
        e = model.emissions(codes, begins)[index].astype(np.float64)
        forward, backward = np.zeros((n, T, L)), np.zeros((n, T, L))
        forward[:, 0] = model.first + e[:, 0]
        for t in range(1, T):
            new = np.logaddexp.reduce(forward[:, t - 1, :, None] + model.step, axis=1) + e[:, t]
            forward[:, t] = np.where(mask[:, t, None], new, forward[:, t - 1])
        for t in range(T - 2, -1, -1):
            new = np.logaddexp.reduce(model.step[None] + (e[:, t + 1] + backward[:, t + 1])[:, None, :], axis=2)
            backward[:, t] = np.where(mask[:, t + 1, None], new, 0)
        z = np.logaddexp.reduce(forward[:, -1], axis=1)
        marginal = np.exp(forward + backward - z[:, None, None])[mask]
        pair = np.exp(forward[:, :-1, :, None] + model.step + (e[:, 1:] + backward[:, 1:])[:, :, None, :] - z[:, None, None, None])[mask[:, 1:]].sum(axis=0)
        truth = np.eye(L)[gold]
        gap = (truth - marginal).astype(np.float32)
        grad = {k: np.zeros_like(getattr(model, k)) for k in squares}
        np.add.at(grad["own"], codes, gap)
        np.add.at(grad["before"], codes[inner - 1], gap[inner])
        np.add.at(grad["after"], codes[inner], gap[inner - 1])
        np.add.at(grad["step"], (gold[inner - 1], gold[inner]), 1)
        grad["step"] -= pair.astype(np.float32)
        grad["first"] = gap[begins].sum(axis=0)
        for k, g in grad.items():
            w = getattr(model, k)
            g = g - decay * len(table) * w
            squares[k] += g * g
            w += rate * g / np.sqrt(squares[k])
    return model


@lru_cache(maxsize=1)
def trained() -> Field:
    return fit(training_table())


def find_batch(model: Field, texts: list[str], data: np.ndarray, offsets: np.ndarray) -> list[list[tuple]]:
    """Spans of each text: the fixed patterns' by kind and start, then the field's by kind and start."""
    starts, ends = _text.spans(~_text.SPACE[data], offsets)
    begins = np.zeros(len(starts), bool)
    doc = np.searchsorted(offsets, starts, "right") - 1
    begins[:1] = True
    begins[1:] = doc[1:] != doc[:-1]
    labels = model.decode(model.emissions(shapes(data, starts, ends), begins), begins)
    marked = np.flatnonzero(labels)
    chains: dict[int, list[tuple[int, int, int]]] = {}
    i = 0
    while i < len(marked):
        j = i
        while j + 1 < len(marked) and marked[j + 1] == marked[j] + 1 and labels[marked[j + 1]] == labels[marked[i]] and not begins[marked[j + 1]]:
            j += 1
        chains.setdefault(int(doc[marked[i]]), []).append((int(labels[marked[i]]), int(starts[marked[i]]), int(ends[marked[j]])))
        i = j + 1
    out = []
    for number, text in enumerate(texts):
        found = base_spans(text)
        extra = []
        if number in chains:
            raw = text.encode()
            begin = int(offsets[number])
            for label, a, b in chains[number]:
                piece = raw[a - begin : b - begin].decode()
                left = len(piece) - len(piece.lstrip("\"'<>[],;:!?|.*"))
                body = piece[left:].rstrip("\"'<>[],;:!?|.*")
                start = len(raw[: a - begin].decode()) + left
                end = start + len(body)
                if plausible(LABELS[label], body) and not any(s[1] < end and start < s[2] for s in found):
                    extra.append((f"crf_{LABELS[label]}", start, end, False, None))
        order = {f"crf_{k}": i for i, k in enumerate(KINDS)}
        out.append(found + sorted(extra, key=lambda s: (order[s[0]], s[1])))
    return out


def plausible(kind: str, body: str) -> bool:
    """What a value of the kind has at least, whatever its neighbours suggest."""
    digits = sum("0" <= c <= "9" for c in body)
    if kind == "email":
        return bool(re.search(r"@|[(\[ ]at[)\] ]", body, re.I)) and bool(re.search(r"\w[.]\w|dot", body, re.I)) and len(body) >= 6
    if kind == "ip":
        return bool(re.fullmatch(r"(\d{1,3}\.){3}\d{1,3}(:\d+)?", body)) and all(int(x) <= 255 for x in body.split(":")[0].split("."))
    if kind == "card":
        return 13 <= digits <= 19 and luhn(re.sub(r"\D", "", body))
    return 9 <= digits <= 15 and bool(re.fullmatch(r"[+(]?[\d() ./-]+", body)) and bool(re.search(r"[()+/-]", body))


def pii_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", carry: bool = False) -> DataFrame:
    """(doc_id, spans) of every row; carry: (row, spans) with the row itself as a struct, so no column's name can clash and no text travels twice."""
    spark = prepare(docs.sparkSession)
    model = spark.sparkContext.broadcast(trained())

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(0).field(text_col) if carry else batch.column(1)
            for first, end, data, offsets in _text.runs(column):
                texts = [x.as_py() or "" for x in column[first:end]]
                found = _spans.batch(batch.column(0)[first:end], find_batch(model.value, texts, data, offsets))
                yield found.rename_columns(["row" if carry else "doc_id", "spans"])

    rows = docs.select(F.struct("*").alias("row")) if carry else docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(work, T.StructType([rows.schema.fields[0], T.StructField("spans", T.DataType.fromDDL(_spans.SPANS))]))


def redact(docs: DataFrame) -> DataFrame:
    """The documents with each span of personal data replaced by its kind in brackets; n_chars follows the text where it is given."""
    found = pii_spans(docs, carry=True)
    old = F.col("row").getField("text")
    spans = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.upper(F.regexp_replace(s["kind"], "crf_", "")).alias("kind"))))
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    # spans of different kinds may overlap: the one that begins first wins, and the rest of a later one goes with it
    step = lambda acc, s: F.when(s["end"] <= acc["at"], acc).otherwise(F.struct(F.concat(acc["out"], F.substring(old, acc["at"] + 1, F.greatest(s["start"] - acc["at"], F.lit(0))), F.lit("["), s["kind"], F.lit("]")).alias("out"), s["end"].alias("at")))
    done = F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substring(old, acc["at"] + 1, F.length(old))))
    rows = found.withColumn("changed", F.when(F.size("spans") > 0, done))
    column = lambda c: F.col("row").getField(c)
    new = {"text": F.coalesce("changed", old)}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("changed").isNull(), column("n_chars")).otherwise(F.length("changed")).cast(docs.schema["n_chars"].dataType)
    return rows.select(*(new.get(c, column(c)).alias(c) for c in docs.columns))

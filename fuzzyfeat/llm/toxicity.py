"""Toxicity scores from a bidirectional gated recurrent network with attention pooling, written and trained in numpy.

Each word enters as the embedding of the word itself (of a vocabulary of the training sample) beside two character inputs,
the mean embedding of its hashed byte trigrams and the embedding of its hashed beginning, so unseen words have an input too. Windows of WINDOW words overlap, every STRIDE words one
begins, and together they cover the whole text; a document scores as its highest window. Training sees documents the same
way: after a warm-up over single windows, each document's gradient goes to its highest window only.

Only the sampled labelled rows are read to fit: at most SAMPLE rows (least hash of doc_id first) whose texts have at most
SAMPLE_CHARS characters. The model is a few hundred kB whatever the input. Held-out labels are never read.

Null and empty texts have no window and score as the base rate. Rows come back as often as they went in. Without labelled
rows of both classes the base rate is the score of every document.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fuzzyfeat.llm import _text
from fuzzyfeat.session import prepare

WINDOW, STRIDE = 32, 24
SAMPLE, SAMPLE_CHARS = 3000, 20_000
VOCABULARY, LEAST_HELD, TRIGRAMS, BEGINNINGS, BEGIN_BYTES = 4096, 4, 4096, 8192, 5
WORD_DIM, CHAR_DIM, BEGIN_DIM, HIDDEN = 10, 6, 8, 8
THRESHOLD, DECAY = 0.3, 0.6
f32 = np.float32


class Tokens:
    """The words of a run of documents: their hashes, byte trigrams and windows."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        letters = ~(_text.SPACE[data] | ((data < 128) & ~_ALNUM[data]))
        lowered = _text.LOWER[data]
        self.starts, self.ends = _text.spans(letters, offsets)
        self.hashes = _text.span_hashes(lowered, self.starts, self.ends)
        self.beginnings = (_text.span_hashes(lowered, self.starts, np.minimum(self.ends, self.starts + BEGIN_BYTES)) % np.uint64(BEGINNINGS)).astype(np.int64)
        padded = np.concatenate([[32], np.where(letters, lowered, 32), [32, 32]]).astype(np.int64)
        self.trigrams = (((padded[:-3] * 961 + padded[1:-2] * 31 + padded[2:-1]) * 2654435761 >> 7) % TRIGRAMS).astype(np.uint16)  # centred on each byte
        first = np.searchsorted(self.starts, offsets)
        count = np.diff(first)
        windows = np.where(count > 0, 1 + np.maximum(0, -(-(count - WINDOW) // STRIDE)), 0)
        self.bounds = np.concatenate([[0], np.cumsum(windows)])
        doc = np.repeat(np.arange(len(count)), windows)
        at = first[doc] + (np.arange(len(doc)) - self.bounds[doc]) * STRIDE
        self.at, self.length = at, np.minimum(WINDOW, first[doc + 1] - at)
        self.first, self.offsets = first, offsets

    @classmethod
    def joined(cls, parts: list["Tokens"]) -> "Tokens":
        """The tokens of all parts, as those of one run."""
        out = cls.__new__(cls)
        n_bytes, n_words, n_windows = (np.cumsum([0] + [len(getattr(p, x)) for p in parts]) for x in ("trigrams", "starts", "at"))
        for name, shift in (("starts", n_bytes), ("ends", n_bytes), ("at", n_words)):
            setattr(out, name, np.concatenate([getattr(p, name) + s for p, s in zip(parts, shift, strict=False)]))
        for name, shift in (("first", n_words), ("offsets", n_bytes), ("bounds", n_windows)):
            setattr(out, name, np.concatenate([np.zeros(1, np.int64)] + [getattr(p, name)[1:] + s for p, s in zip(parts, shift, strict=False)]))
        for name in ("hashes", "beginnings", "trigrams", "length"):
            setattr(out, name, np.concatenate([getattr(p, name) for p in parts]))
        return out

    def part(self, a: int, b: int) -> "Tokens":
        """The tokens of documents a to b."""
        out = Tokens.__new__(Tokens)
        byte, word, window = (slice(x[a], x[b]) for x in (self.offsets, self.first, self.bounds))
        out.trigrams, out.hashes, out.beginnings, out.length = self.trigrams[byte], self.hashes[word], self.beginnings[word], self.length[window]
        out.starts, out.ends, out.at = self.starts[word] - byte.start, self.ends[word] - byte.start, self.at[window] - word.start
        out.offsets, out.first, out.bounds = self.offsets[a : b + 1] - byte.start, self.first[a : b + 1] - word.start, self.bounds[a : b + 1] - window.start
        return out

    def chars(self, table: np.ndarray) -> np.ndarray:
        """Mean trigram embedding of each word."""
        if not len(self.starts):
            return np.zeros((0, table.shape[1]), f32)
        edges = np.stack([self.starts, self.ends], 1).reshape(-1)
        rows = table[np.append(self.trigrams, np.uint16(0))]
        return np.add.reduceat(rows, edges, axis=0)[::2] / (self.ends - self.starts)[:, None].astype(f32)


_ALNUM = np.zeros(256, bool)
_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


def _summed(index: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows by index."""
    return np.stack([np.bincount(index, rows[:, j], n) for j in range(rows.shape[1])], 1).astype(f32)


class Network:
    def __init__(self, vocabulary: np.ndarray, seed: int = 5):
        g = np.random.default_rng(seed)
        make = lambda *shape, s=0.3: (g.standard_normal(shape) * s).astype(f32)
        dim = WORD_DIM + CHAR_DIM + BEGIN_DIM
        self.vocabulary = vocabulary  # sorted word hashes; id 0 is any other word
        self.p = {"words": make(len(vocabulary) + 1, WORD_DIM), "chars": make(TRIGRAMS, CHAR_DIM, s=0.15), "begins": make(BEGINNINGS, BEGIN_DIM, s=0.15), "attend": make(2 * HIDDEN, HIDDEN), "query": make(HIDDEN), "out": make(2 * HIDDEN), "bias": np.array([-1.0], f32)}
        for side in "fb":
            self.p |= {f"wx{side}": make(dim, 3 * HIDDEN), f"wh{side}": make(HIDDEN, 3 * HIDDEN), f"b{side}": np.zeros(3 * HIDDEN, f32)}
        self.base, self.constant = 0.0, False
        self.moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in self.p.items()}
        self.steps = 0

    def ids(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.vocabulary):
            return np.zeros(len(hashes), np.int64)
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, at + 1, 0)

    def inputs(self, tokens: Tokens) -> np.ndarray:
        return np.concatenate([self.p["words"][self.ids(tokens.hashes)], tokens.chars(self.p["chars"]), self.p["begins"][tokens.beginnings]], axis=1)

    def forward(self, x: np.ndarray, at: np.ndarray, length: np.ndarray, keep: bool = False):
        """Logits of the windows that begin at rows `at` of x. keep: with what the backward pass needs."""
        p, n, H = self.p, len(at), HIDDEN
        steps = int(length.max()) if n else 0
        mask = np.arange(steps)[None, :] < length[:, None]
        index = np.minimum(at[:, None] + np.arange(steps)[None, :], max(len(x) - 1, 0))
        states = np.zeros((n, steps, 2 * H), f32)
        kept = {}
        for side, order in (("f", range(steps)), ("b", range(steps - 1, -1, -1))):
            z_in = x @ p[f"wx{side}"] + p[f"b{side}"]
            h, lane, memory = np.zeros((n, H), f32), slice(0, H) if side == "f" else slice(H, 2 * H), {}
            for t in order:
                a, u = z_in[index[:, t]], h @ p[f"wh{side}"]
                gates = sigmoid(a[:, : 2 * H] + u[:, : 2 * H])
                z, r = gates[:, :H], gates[:, H:]
                c = np.tanh(a[:, 2 * H :] + r * u[:, 2 * H :])
                m = mask[:, t, None]
                new = np.where(m, c + z * (h - c), h)
                if keep:
                    memory[t] = (h, z, r, c, u[:, 2 * H :], m)
                h = new
                states[:, t, lane] = h
            kept[side] = memory
        hidden = np.tanh(states @ p["attend"])
        score = np.where(mask, hidden @ p["query"], f32(-1e9))
        weight = np.exp(score - score.max(axis=1, keepdims=True)) if n else score
        weight /= weight.sum(axis=1, keepdims=True)
        pooled = np.einsum("nt,nth->nh", weight, states)
        logit = pooled @ p["out"] + p["bias"][0]
        return (logit, (x, index, mask, states, kept, hidden, weight, pooled)) if keep else logit

    def backward(self, memory, d_logit: np.ndarray) -> tuple[dict[str, np.ndarray], np.ndarray, np.ndarray]:
        """Gradients of the parameters, and the rows of x with theirs."""
        p, H = self.p, HIDDEN
        x, index, mask, states, kept, hidden, weight, pooled = memory
        grad = {"out": d_logit @ pooled, "bias": np.array([d_logit.sum()], f32)}
        d_pooled = d_logit[:, None] * p["out"]
        d_weight = np.einsum("nh,nth->nt", d_pooled, states)
        d_states = weight[:, :, None] * d_pooled[:, None, :]
        d_score = weight * (d_weight - (weight * d_weight).sum(axis=1, keepdims=True))
        grad["query"] = d_score.reshape(-1) @ hidden.reshape(-1, H)
        d_hidden = d_score[:, :, None] * p["query"] * (1 - hidden**2)
        grad["attend"] = states.reshape(-1, 2 * H).T @ d_hidden.reshape(-1, H)
        d_states += d_hidden @ p["attend"].T
        rows, n_steps = index.reshape(-1), index.shape[1]
        d_x = np.zeros((*index.shape, x.shape[1]), f32)
        for side, order in (("f", range(n_steps - 1, -1, -1)), ("b", range(n_steps))):
            lane = slice(0, H) if side == "f" else slice(H, 2 * H)
            d_wh, d_a_all, d_h = np.zeros_like(p[f"wh{side}"]), np.zeros((*index.shape, 3 * H), f32), np.zeros((len(index), H), f32)
            for t in order:
                h, z, r, c, u, m = kept[side][t]
                d = d_h + d_states[:, t, lane]
                d_new = np.where(m, d, 0)
                d_z = d_new * (h - c) * z * (1 - z)
                d_c = d_new * (1 - z) * (1 - c**2)
                d_r = d_c * u * r * (1 - r)
                d_u = np.concatenate([d_z, d_r, d_c * r], axis=1)
                d_a_all[:, t] = np.concatenate([d_z, d_r, d_c], axis=1)
                d_wh += h.T @ d_u
                d_h = np.where(m, d_new * z, d) + d_u @ p[f"wh{side}"].T
            grad[f"wh{side}"], grad[f"b{side}"] = d_wh, d_a_all.sum(axis=(0, 1))
            grad[f"wx{side}"] = x[rows].T @ d_a_all.reshape(-1, 3 * H)
            d_x += d_a_all @ p[f"wx{side}"].T
        used = mask.reshape(-1)
        return grad, rows[used], d_x.reshape(-1, x.shape[1])[used]

    def step(self, grad: dict[str, np.ndarray], rate: float) -> None:
        """One Adam step."""
        self.steps += 1
        for k, g in grad.items():
            m, v = self.moments[k]
            if k in ("words", "chars", "begins"):
                self.p[k] *= f32(1 - rate * DECAY)
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            self.p[k] -= (rate * (m / (1 - 0.9**self.steps)) / (np.sqrt(v / (1 - 0.999**self.steps)) + 1e-8)).astype(f32)

    def learn(self, tokens: Tokens, windows: np.ndarray, targets: np.ndarray, rate: float) -> None:
        at, length = tokens.at[windows], tokens.length[windows]
        rows = np.unique((at[:, None] + np.arange(WINDOW))[np.arange(WINDOW)[None, :] < length[:, None]])
        ids = self.ids(tokens.hashes[rows])
        begin, size = tokens.starts[rows], (tokens.ends - tokens.starts)[rows]
        word_of = np.repeat(np.arange(len(rows)), size)
        tri = tokens.trigrams[np.repeat(begin, size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)]
        chars = np.add.reduceat(self.p["chars"][tri], np.cumsum(size) - size, axis=0)
        x = np.concatenate([self.p["words"][ids], chars / size[:, None].astype(f32), self.p["begins"][tokens.beginnings[rows]]], axis=1)
        logit, memory = self.forward(x, np.searchsorted(rows, at), length, keep=True)
        grad, used, d_x = self.backward(memory, ((sigmoid(logit) - targets) / len(windows)).astype(f32))
        total = _summed(used, d_x, len(x))
        grad["words"] = _summed(ids, total[:, :WORD_DIM], len(self.p["words"]))
        grad["chars"] = _summed(tri, (total[:, WORD_DIM : WORD_DIM + CHAR_DIM] / size[:, None].astype(f32))[word_of], TRIGRAMS)
        grad["begins"] = _summed(tokens.beginnings[rows], total[:, WORD_DIM + CHAR_DIM :], BEGINNINGS)
        self.step(grad, rate)

    def window_logits(self, tokens: Tokens) -> np.ndarray:
        return self.forward(self.inputs(tokens), tokens.at, tokens.length) if len(tokens.at) else np.zeros(0, f32)

    def document_scores(self, tokens: Tokens) -> np.ndarray:
        count = np.diff(tokens.bounds)
        out = np.full(len(count), self.base, np.float64)
        if count.any() and not self.constant:
            out[count > 0] = sigmoid(np.maximum.reduceat(self.window_logits(tokens), tokens.bounds[:-1][count > 0]).astype(np.float64))
        return out


def fit(texts: list[str], labels: list[int], seed: int = 5, warm_up: int = 200, steps: int = 40, rounds: int = 8, batch: int = 128) -> Network:
    """Train on labelled texts: warm_up steps on single windows, then at least `steps` on whole documents through their highest window."""
    labels = np.asarray(labels, f32)
    column = pa.array(texts, pa.large_string())
    parts = [Tokens(data, offsets) for _, _, data, offsets in _text.runs(column)]
    said = np.concatenate([np.diff(p.bounds) > 0 for p in parts]) if parts else np.zeros(0, bool)
    if not (said & (labels == 1)).any() or not (said & (labels == 0)).any():
        model = Network(np.zeros(0, np.uint64), seed)
        model.base, model.constant = float(labels.mean()) if len(labels) else 0.0, True
        return model
    tokens = Tokens.joined(parts)
    del parts
    doc_of = np.repeat(np.arange(len(texts)), np.diff(tokens.bounds))
    known, held = np.unique(np.concatenate([np.unique(tokens.hashes[tokens.first[d] : tokens.first[d + 1]]) for d in range(len(texts))]), return_counts=True)
    known, held = known[held >= LEAST_HELD], held[held >= LEAST_HELD]
    model = Network(np.sort(known[np.lexsort((known, -held))[:VOCABULARY]]), seed)
    model.base = float(labels.mean())
    g = np.random.default_rng(seed)
    positive = np.flatnonzero(labels[doc_of] == 1)
    negative = np.flatnonzero(labels[doc_of] == 0)
    for _ in range(warm_up):
        some = np.concatenate([g.choice(positive, batch // 2), g.choice(negative, batch // 2)])
        model.learn(tokens, some, labels[doc_of[some]], 0.01)
    count = np.diff(tokens.bounds)
    full = np.flatnonzero(count)
    rounds = max(rounds, -(-steps * batch // len(full)))
    for turn in range(rounds):
        logits = np.concatenate([model.window_logits(tokens.part(a, min(a + 200, len(texts)))) for a in range(0, len(texts), 200)])
        top = np.array([tokens.bounds[d] + np.argmax(logits[tokens.bounds[d] : tokens.bounds[d + 1]]) for d in full])
        some = g.permutation(len(full))
        for at in range(0, len(some), batch):
            chosen = some[at : at + batch]
            model.learn(tokens, top[chosen], labels[full[chosen]], 0.006 if turn < 0.7 * rounds else 0.002)
    return model


def held_out(id_col: str = "doc_id"):
    """Rows whose labels are never learned from: crc32 of the id as text leaves 2 on division by 4."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, max_chars: int = SAMPLE_CHARS) -> DataFrame:
    """(doc_id, text, toxic): the bounded sample of labelled texts."""
    named = labels.filter(~held_out()).filter(F.col("toxic").isin(0, 1)).select("doc_id", "toxic")
    named = named.orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(sample)
    return docs.select("doc_id", "text").filter(F.length("text") <= max_chars).join(F.broadcast(named), "doc_id").select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("toxic").cast("int").alias("toxic")).limit(2 * sample)


def fitted(docs: DataFrame, labels: DataFrame) -> Network:
    """The network of the labelled sample, trained in one task of an executor: the driver holds neither texts nor training state."""
    prepare(docs.sparkSession)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted(((i, t or "", y) for b in batches for i, t, y in zip(*(c.to_pylist() for c in b.columns), strict=True)))
        model = fit([t for _, t, _ in rows], [y for *_, y in rows])
        model.moments = {}
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])

    found = training_rows(docs, labels).mapInArrow(work, "model binary").collect()
    return pickle.loads(found[0]["model"]) if found else fit([], [])


def score(docs: DataFrame, model: Network, carry: bool = False) -> DataFrame:
    """(doc_id, score) of every row; carry: (row, score) with the row itself as a struct, so no column's name can clash and no text travels twice."""
    spark = prepare(docs.sparkSession)
    model.moments = {}
    shared = spark.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, end, data, offsets in _text.runs(batch.column(0).field("text") if carry else batch.column(1)):
                yield pa.RecordBatch.from_arrays([batch.column(0)[first:end], pa.array(shared.value.document_scores(Tokens(data, offsets)))], ["row" if carry else "doc_id", "score"])

    rows = docs.select(F.struct("*").alias("row")) if carry else docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(work, T.StructType([rows.schema.fields[0], T.StructField("score", T.DoubleType())]))


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document, by a network fitted on the labelled sample."""
    model = fitted(docs, labels)
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score under the threshold, as they came: scored and filtered in one pass."""
    model = fitted(docs, labels)
    return score(docs, model, carry=True).filter(F.col("score") < threshold).select(*(F.col("row").getField(c).alias(c) for c in docs.columns))

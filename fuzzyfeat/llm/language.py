"""Language of web pages by Bayesian fusion of evidence.

A page's posterior over the languages is the product of
- the likelihood of its text under byte-trigram models, tempered so that a short text says little and none too much,
- the likelihood of the declared markup language, and of the address's suffix and path segment, given each language,
- a prior of its host, smoothed towards the prior of its domain suffix, and that towards the prior of all pages.

The trigram models are fitted on a bounded sample of labelled documents (SAMPLE of the least hash). Everything else is
counted over all pages by grouped aggregation of their text likelihoods, so no row is declared right beforehand. Counts are
pre-aggregated before they are dealt out; up to BROADCAST_KEYS hosts are broadcast, and beyond that a hot host is only
joined by narrow rows, which adaptive execution may split.

Null or empty pages have no text evidence; a null url has neither host nor suffix; what is missing says nothing. Rows come
back as often as they went in. An empty table, or one without labelled documents, gives the language null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.llm import _text
from fuzzyfeat.session import materialise, prepare

SAMPLE, SAMPLE_CHARS, CELLS = 4000, 20_000, 1 << 15
TEMPER, SMOOTH_HOST, SMOOTH_SUFFIX = 0.05, 20.0, 50.0
BROADCAST_KEYS = 100_000


def trigram_cells(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells of the byte trigrams that begin in each document, and the document of each."""
    if len(data) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    low = _text.LOWER[data].astype(np.int64)
    cells = (low[:-2] * 65599 + low[1:-1] * 257 + low[2:]) * 2654435761 >> 9 & CELLS - 1
    at = np.arange(len(cells))
    doc = np.searchsorted(offsets, at, "right") - 1
    inside = at + 3 <= offsets[doc + 1]
    return cells[inside], doc[inside]


class TrigramModel:
    def __init__(self, texts: list[str], languages: list[str]):
        self.languages = sorted(set(languages))
        counts = np.full((len(self.languages), CELLS), 0.5)
        for code, language in enumerate(self.languages):
            for _, _, data, offsets in _text.runs(pa.array([t for t, x in zip(texts, languages, strict=True) if x == language], pa.large_string())):
                counts[code] += np.bincount(trigram_cells(data, offsets)[0], minlength=CELLS)
        logs = np.log(counts / counts.sum(axis=1, keepdims=True))
        self.table = (logs - logs.mean(axis=0)).T.astype(np.float32) if len(logs) else logs.T

    def scores(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Tempered log-likelihoods: the sum over a text's trigrams, times TEMPER, within +-12."""
        cells, doc = trigram_cells(data, offsets)
        out = np.zeros((len(offsets) - 1, len(self.languages)))
        for j in range(len(self.languages)):
            out[:, j] = np.bincount(doc, self.table[cells, j], len(out))
        out *= TEMPER
        out -= out.max(axis=1, keepdims=True) if len(self.languages) else 0
        return np.maximum(out, -12.0)


def fit(docs: DataFrame, sample: int = SAMPLE) -> TrigramModel:
    usable = docs.filter(F.col("lang").isNotNull() & (F.length("text") > 0) & (F.length("text") <= SAMPLE_CHARS)).select("doc_id", "lang", "text")
    ids = usable.select("doc_id").filter("doc_id IS NOT NULL").orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)  # tasks send ids, not texts
    some = usable.join(F.broadcast(ids.distinct()), "doc_id").limit(2 * sample).collect()
    some.sort(key=lambda r: (r["doc_id"], r["lang"], r["text"]))
    return TrigramModel([r["text"] for r in some], [r["lang"] for r in some])


def address_evidence(url: Column) -> dict[str, Column]:
    """Host, domain suffix and language-like path segment of an address; null where there is none."""
    some = lambda c: F.when(c != "", c)
    host = some(F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1)))
    return {"host": host, "suffix": some(F.regexp_extract(host, r"\.([a-z]{2,})$", 1)), "segment": some(F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/]*/([a-zA-Z]{2})(?:[-_][a-zA-Z]{2})?(?:[/?#]|$)", 1)))}


def declared_language(html: Column) -> Column:
    """The primary subtag of the html element's lang, or of a content-language meta element."""
    tag = F.regexp_extract(html, r"(?i)<html\b[^>]*?\slang\s*=\s*[\"']?([a-zA-Z]{2,3})", 1)
    meta = F.regexp_extract(html, r"(?i)<meta\b[^>]*content-language[^>]*content\s*=\s*[\"']?([a-zA-Z]{2,3})", 1)
    return F.when(tag != "", F.lower(tag)).when(meta != "", F.lower(meta))


def visible_text(html: Column) -> Column:
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    return F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"&[a-zA-Z#0-9]{1,8};", " ")


def _shares(rows: DataFrame, key: str, n: int) -> DataFrame:
    """key, total and the summed text posteriors of the rows with each key: partial sums first, so a hot key is no burden."""
    return rows.filter(F.col(key).isNotNull()).groupBy(key).agg(*(F.sum(F.get("post", F.lit(j))).alias(f"s{j}") for j in range(n)), F.count("*").alias("total"))


def _softmax(scores: Column) -> Column:
    top = F.array_max(scores)
    weights = F.transform(scores, lambda x: F.exp(x - top))
    total = F.aggregate(weights, F.lit(0.0), lambda s, x: s + x)
    return F.transform(weights, lambda x: x / total)


def identify(pages: DataFrame, docs: DataFrame) -> DataFrame:
    """(page_id, lang, confidence, text_lang, declared, suffix, segment, host) of every row."""
    spark = prepare(pages.sparkSession)
    model = fit(docs)
    n = len(model.languages)
    evidence = pages.select("page_id", F.col("html"), F.col("url")).select("page_id", visible_text(F.col("html")).alias("text"), declared_language(F.col("html")).alias("declared"), *(c.alias(k) for k, c in address_evidence(F.col("url")).items()))
    if not n:
        return evidence.select("page_id", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("confidence"), F.lit(None).cast("string").alias("text_lang"), "declared", "suffix", "segment", "host")
    shared = spark.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, end, data, offsets in _text.runs(batch.column(1)):
                part = batch.slice(first, end - first)
                scores = pa.FixedSizeListArray.from_arrays(pa.array(shared.value.scores(data, offsets).reshape(-1)), n).cast(pa.list_(pa.float64()))
                yield pa.RecordBatch.from_arrays([part.column(0), *part.columns[2:], scores], ["page_id", "declared", "host", "suffix", "segment", "scores"])

    scored = evidence.select("page_id", "text", "declared", "host", "suffix", "segment").mapInArrow(work, f"page_id {pages.schema['page_id'].dataType.simpleString()}, declared string, host string, suffix string, segment string, scores array<double>")
    scored = materialise(scored.withColumn("post", _softmax(F.col("scores"))))
    whole = [x or 0 for x in scored.agg(*(F.sum(F.get("post", F.lit(j))) for j in range(n)), F.count("*")).first()]
    prior = [(whole[j] + 1) / (whole[n] + n) for j in range(n)]
    rows = scored

    for key in ("declared", "segment", "suffix", "host"):
        shares = _shares(scored, key, n)
        shares = materialise(shares.select(F.concat(key, F.lit("")).alias(key), F.array(*(f"s{j}" for j in range(n))).alias(f"{key}_s"), F.col("total").alias(f"{key}_t")))
        # Few values: the rows stay where they are, in as many tasks as there were. Many, such as all hosts of a crawl: a join that may split a hot one.
        rows = rows.join(F.broadcast(shares) if shares.count() <= BROADCAST_KEYS else shares, key, "left")

    lane = range(n)
    at = lambda c, j: F.get(c, F.lit(j))
    # P(value | language), smoothed towards P(value)
    given = lambda key, j: F.coalesce(F.log((at(f"{key}_s", j) + 5 * F.col(f"{key}_t") / (whole[n] or 1)) / (whole[j] + 5) / (F.col(f"{key}_t") / (whole[n] or 1))), F.lit(0.0))
    suffix = [F.coalesce((at("suffix_s", j) + SMOOTH_SUFFIX * prior[j]) / (F.col("suffix_t") + SMOOTH_SUFFIX), F.lit(prior[j])) for j in lane]
    host = [F.coalesce((at("host_s", j) - at("post", j) + SMOOTH_HOST * suffix[j]) / (F.col("host_t") - 1 + SMOOTH_HOST), suffix[j]) for j in lane]
    total = F.array(*(at("scores", j) + given("declared", j) + given("segment", j) + F.log(F.greatest(host[j], F.lit(1e-6))) for j in lane))
    names = F.array(*(F.lit(x) for x in model.languages))
    done = rows.withColumn("final", _softmax(total))
    best = F.array_max("final")
    name_of = lambda c, top: F.get(names, (F.array_position(c, top) - 1).cast("int"))
    return done.select("page_id", name_of(F.col("final"), best).alias("lang"), best.alias("confidence"), name_of(F.col("post"), F.array_max("post")).alias("text_lang"), "declared", "suffix", "segment", "host")

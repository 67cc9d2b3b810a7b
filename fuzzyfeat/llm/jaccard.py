"""N-gram Jaccard join of documents: a grouped prefix join that yields the classes of linked documents.

Words are runs of characters other than U+0020 and U+0009-U+000D, A-Z lower-cased; a document's set holds its distinct
k-word shingles (all its words as one shingle, if it has fewer than k). Two documents link when
denominator * |intersection| >= numerator * |union|.

The steps:

1. A counting sketch over the shingles of all documents gives one order of shingles for all, rare ones first. Two linked
   sets of that order share one of their first n - ceil(t n) + 1 shingles (the prefix). Any common order is right; this
   one keeps what thousands of documents share out of the prefixes.
2. Documents with equal sets collapse into one; those with the same size and prefix collapse into a group.
3. Groups meet in the buckets of their prefix shingles. Sizes, and what is left of both sets behind the first shingle that
   they share, rule a pair out inside the join. First each member meets the bucket's least member (its pivot), so a bucket
   of copies costs one comparison for each.
4. What is left are members of one bucket in different components. The bucket's largest component stays whole on one side
   of the join, so copies never meet each other; sizes are part of its key.
5. Pairs that are left expand to the members of their groups; signatures rule out what can't link, and sets are compared.

Rows of a null or empty text, or of one without words, have an empty set and link with nothing. doc_id is the key: rows
repeated as a whole come back as often as they went in, with one component.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.llm import _text
from fuzzyfeat.llm._graph import components
from fuzzyfeat.session import materialise, prepare, release, scratch

SKETCH_BITS = 20
SKETCH_PART = 14
BROADCAST_IDS = 500_000
_SIGNED = np.int64


def _columns(batch: pa.RecordBatch) -> tuple[np.ndarray, pa.Array]:
    return np.asarray(batch.column(0).to_numpy(zero_copy_only=False), dtype=np.int64), batch.column(1)


def prefix_length(n: np.ndarray, numerator: int, denominator: int) -> np.ndarray:
    """How many of its first shingles a set of n must share one of with any set that it links with."""
    return np.where(n > 0, n - -(-n * numerator // denominator) + 1, 0)


def _sketch_rows(k: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << SKETCH_BITS, np.int64)
        for batch in batches:
            for _, _, data, offsets in _text.runs(batch.column(0)):
                values, _ = _text.shingle_sets(data, offsets, k)
                counts += np.bincount((values >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=len(counts))
        parts = counts.reshape(-1, 1 << SKETCH_PART)
        used = np.flatnonzero(parts.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array([parts[i].astype("<u4").tobytes() for i in used], pa.binary())], ["part", "counts"])

    return work


def _sketch_sum(key, table):
    total = np.zeros(1 << SKETCH_PART, np.int64)
    for x in table.column("counts"):
        total += np.frombuffer(x.as_py(), "<u4" if len(x.as_py()) == 4 << SKETCH_PART else "<i8")
    return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "counts": pa.array([total.tobytes()], pa.binary())})


def shingle_sketch(docs: DataFrame, k: int, text_col: str = "text") -> np.ndarray:
    """Counts of the shingle sets of all documents in 2 ** SKETCH_BITS cells: a result of fixed size."""
    rows = docs.select(F.col(text_col).alias("text")).mapInArrow(_sketch_rows(k), "part int, counts binary")
    counts = np.zeros((1 << (SKETCH_BITS - SKETCH_PART), 1 << SKETCH_PART), np.int64)
    for row in rows.groupBy("part").applyInArrow(_sketch_sum, "part int, counts binary").collect():
        counts[row["part"]] = np.frombuffer(row["counts"], "<i8")
    return counts.reshape(-1)


def _levels(counts: np.ndarray) -> np.ndarray:
    """The rank of each cell's shingles in the common order: its count. What a dozen documents share stands out from a cell's usual load."""
    return np.minimum(counts, 2**32 - 1).astype(np.uint32)


def _ordered(values: np.ndarray, bounds: np.ndarray, level: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The shingles of each document in the common order, rare ones first, and the document of each."""
    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    order = np.lexsort((values, level[(values >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], doc))
    return values[order], doc


def _in_prefix(bounds: np.ndarray, doc: np.ndarray, numerator: int, denominator: int) -> np.ndarray:
    length = prefix_length(np.diff(bounds), numerator, denominator)
    return np.arange(len(doc)) - bounds[doc] < length[doc]


def _sums(values: np.ndarray, doc: np.ndarray, n_docs: int) -> np.ndarray:
    """Sum of the values of each document, modulo 2 ** 64."""
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values, dtype=np.uint64)])
    bounds = np.searchsorted(doc, np.arange(n_docs + 1))
    return total[bounds[1:]] - total[bounds[:-1]]


def signature_bits(n: np.ndarray) -> np.ndarray:
    """Bits of the signature of a set of n: the least power of two that holds n, 64 at least."""
    return 2 ** np.ceil(np.log2(np.maximum(64, n))).astype(np.int64)


def signatures(values: np.ndarray, doc: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Parity signatures as 64-bit words, and their bounds: bit i tells if an odd number of shingles have i as hash modulo the bits.

    Two signatures of one length differ in at most |A xor B| bits; folding the halves by xor gives that of half the length.
    """
    bits = signature_bits(n)
    begin = np.concatenate([[0], np.cumsum(bits)])
    odd = np.bincount(begin[doc] + (values & (bits[doc] - 1).astype(np.uint64)).astype(np.int64), minlength=begin[-1]) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8"), begin // 64


def _profile_rows(k: int, numerator: int, denominator: int, levels):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = levels.value
        for batch in batches:
            ids, texts = _columns(batch)
            for first, end, data, offsets in _text.runs(texts):
                values, bounds = _text.shingle_sets(data, offsets, k)
                ordered, doc = _ordered(values, bounds, level)
                inside = _in_prefix(bounds, doc, numerator, denominator)
                sums = [_sums(_text.mix(x), d, end - first) for x, d in ((ordered, doc), (ordered ^ np.uint64(0x5BD1E995), doc), (ordered[inside] + np.uint64(9), doc[inside]))]
                words, begin = signatures(ordered, doc, np.diff(bounds))
                signature = pa.ListArray.from_arrays(pa.array(begin, pa.int32()), pa.array(words))
                yield pa.RecordBatch.from_arrays([pa.array(ids[first:end]), pa.array(np.diff(bounds), pa.int64()), *(pa.array(x.view(_SIGNED)) for x in sums), signature], ["doc_id", "n", "d1", "d2", "g", "signature"])

    return work


def _posting_rows(k: int, numerator: int, denominator: int, levels):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = levels.value
        for batch in batches:
            ids, texts = _columns(batch)
            for first, end, data, offsets in _text.runs(texts):
                values, bounds = _text.shingle_sets(data, offsets, k)
                ordered, doc = _ordered(values, bounds, level)
                inside = _in_prefix(bounds, doc, numerator, denominator)
                n, at = np.diff(bounds)[doc], np.arange(len(doc)) - bounds[doc]
                yield pa.RecordBatch.from_arrays([pa.array(ordered[inside].view(_SIGNED)), pa.array(ids[first:end][doc[inside]]), pa.array(n[inside], pa.int32()), pa.array(at[inside], pa.int32())], ["token", "node", "n", "at"])

    return work


def _set_rows(k: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = _columns(batch)
            for first, end, data, offsets in _text.runs(texts):
                values, bounds = _text.shingle_sets(data, offsets, k)
                sets = pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(values.view(_SIGNED)))
                yield pa.RecordBatch.from_arrays([pa.array(ids[first:end]), sets], ["node", "s"])

    return work


def _anew(name: str):
    """The key as an expression: a join deals this side out again, so that adaptive execution may split the other at a hot key."""
    return (F.col(name) + F.lit(0)).alias(name)


class _Comparer:
    """Compares pairs of nodes: by the signatures of their sets, and by the sets where those don't decide."""

    def __init__(self, docs: DataFrame, light: DataFrame, k: int, numerator: int, denominator: int):
        self.docs, self.light, self.k, self.numerator, self.denominator = docs, light, k, numerator, denominator

    def may_meet(self, n: str, at: str, n2: str, at2: str):
        """If two sets of n and n2 shingles can link whose first common shingle is their at-th and at2-th (from 0).

        They link with numerator * (n + n2) <= (numerator + denominator) * |A and B| only, and what they share lies behind those.
        """
        n, at, n2, at2 = (F.col(c).cast("long") for c in (n, at, n2, at2))
        return (F.least(n, n2) * self.denominator >= F.greatest(n, n2) * self.numerator) & (F.least(n - at, n2 - at2) * (self.numerator + self.denominator) >= (n + n2) * self.numerator)

    def may_link(self, pairs: DataFrame) -> DataFrame:
        """The pairs (u, v) that sizes and signatures don't rule out: these differ in at most |A xor B| bits."""
        sides = (self.light.select(F.col("node").alias(side), F.col("n").alias(f"n_{side}"), F.col("signature").alias(f"s_{side}")) for side in ("u", "v"))
        x, total = self.apart("s_u", "s_v", "n_u", "n_v"), F.col("n_u") + F.col("n_v")
        may = x * (self.numerator + self.denominator) <= total * (self.denominator - self.numerator)
        left, right = sides
        return pairs.join(left, "u").join(right.withColumnRenamed("v", "w"), (F.col("v") == F.col("w")) & may).select("u", "v")

    @classmethod
    def apart(cls, a: str, b: str, n_a: str, n_b: str):
        """A lower bound of |A xor B|: the bits in which the signatures differ, or the difference of the sizes.

        Sets of sizes that can link have signatures of one length or of twice that; the sizes speak for the others.
        """
        one, two, sizes = cls._folded(a, b), cls._folded(b, a), F.abs(F.col(n_a) - F.col(n_b))
        bits = F.aggregate(F.zip_with(one, two, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x).cast("long")
        return F.when(F.size(one) == F.size(two), F.greatest(bits, sizes)).otherwise(sizes)

    @staticmethod
    def _folded(a: str, b: str):
        """Signature a in half as many bits, if b has fewer."""
        half = (F.size(a) / 2).cast("int")
        folded = F.zip_with(F.slice(a, F.lit(1), half), F.slice(a, half + 1, half), lambda x, y: x.bitwiseXOR(y))
        return F.when(F.size(a) > F.size(b), folded).otherwise(F.col(a))

    def texts_of(self, ids: DataFrame) -> DataFrame:
        """The documents with the given ids; these are broadcast to the scan only up to a checked count."""
        return self.docs.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, "doc_id", "left_semi")

    def sets_of(self, ids: DataFrame) -> DataFrame:
        """(node, s) of the nodes in ids."""
        texts = self.texts_of(materialise(ids.distinct()))
        return texts.mapInArrow(_set_rows(self.k), "node long, s array<long>").filter(F.size("s") > 0).dropDuplicates(["node"])

    def linked(self, pairs: DataFrame) -> DataFrame:
        """The pairs (u, v) that link."""
        like = materialise(self.may_link(pairs))
        sets = self.sets_of(like.select(F.col("u").alias("doc_id")).unionByName(like.select(F.col("v").alias("doc_id"))))
        met = like.join(sets.select(F.col("node").alias("u"), F.col("s").alias("su")), "u").join(sets.select(_anew("node").alias("v"), F.col("s").alias("sv")), "v")
        met = met.withColumn("both", F.size(F.array_intersect("su", "sv")).cast("long"))
        met = met.withColumn("all", F.size("su") + F.size("sv") - F.col("both"))
        found = materialise(met.filter(F.col("both") * self.denominator >= F.col("all") * self.numerator).select("u", "v"))
        release(like)
        return found


def jaccard_components(docs: DataFrame, k: int = 5, threshold: tuple[int, int] = (80, 100), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row: component_id is the least doc_id reachable by links, itself included.

    Null or wordless texts: n_shingles 0 and their own id. Rows without an id link with nothing and have no component. Equal sets always link. Extra columns of `docs` are ignored.
    An empty table gives an empty result.
    """
    spark = prepare(docs.sparkSession)
    numerator, denominator = threshold
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    nameless = docs.filter("doc_id IS NULL").select(F.lit(0).cast("long").alias("doc_id"), "text").mapInArrow(_set_rows(k), "node long, s array<long>")
    docs = docs.filter("doc_id IS NOT NULL")
    levels = spark.sparkContext.broadcast(_levels(shingle_sketch(docs, k)))
    profile = materialise(docs.mapInArrow(_profile_rows(k, numerator, denominator, levels), "doc_id long, n long, d1 long, d2 long, g long, signature array<long>"))
    # Equal sets collapse; of each, the least id is the node.
    nodes = materialise(profile.filter("n > 0").groupBy("n", "d1", "d2").agg(F.min(F.struct("doc_id", "g", "signature")).alias("x")).select("n", "d1", "d2", F.col("x.doc_id").alias("node"), "x.g", "x.signature"))
    # Equal size and prefix: one group, whose least node leads it.
    groups = nodes.groupBy("n", "g").agg(F.min("node").alias("leader"))
    members = materialise(nodes.select("n", "g", "node").join(groups.select(_anew("n"), "g", "leader"), ["n", "g"]).select("node", "leader", "n"))
    comparer = _Comparer(docs, nodes.select("node", "n", "signature"), k, numerator, denominator)
    leaders = comparer.texts_of(members.filter("node = leader").select(F.col("node").alias("doc_id")))
    postings = leaders.mapInArrow(_posting_rows(k, numerator, denominator, levels), "token long, node long, n int, at int")
    pivots = postings.groupBy("token").agg(F.min(F.struct("node", "n", "at")).alias("p"), F.count("*").alias("held")).filter("held > 1")
    joined = postings.join(pivots.select(_anew("token"), F.col("p.node").alias("pivot"), F.col("p.n").alias("n2"), F.col("p.at").alias("at2")), "token")
    with scratch(spark) as keep:
        shared = keep(joined)
        # Members with their leader, and buckets with their pivot.
        inside = members.filter("node != leader").select(F.col("node").alias("u"), F.col("leader").alias("v"))
        first = shared.filter("node != pivot").filter(comparer.may_meet("n", "at", "n2", "at2")).select(F.col("node").alias("u"), F.col("pivot").alias("v")).distinct()
        seen = materialise(inside.unionByName(first))
        linked = comparer.linked(seen)
        labels = components(linked)
        last = _remaining(comparer, shared, members, seen, labels, keep)
    if not last.isEmpty():
        more = comparer.linked(last)
        if not more.isEmpty():
            labels = components(linked.unionByName(more))
        release(more)
    release(members, seen, linked, last)
    # Back to rows: node -> component, then every document through its set.
    named = nodes.select("n", "d1", "d2", "node").join(labels, "node", "left").select(_anew("n"), "d1", "d2", F.coalesce("component", "node").alias("component_id"))
    whole = profile.filter("n > 0").select("doc_id", "n", "d1", "d2").join(named, ["n", "d1", "d2"]).select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    empty = profile.filter("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    nobody = F.lit(None).cast("long")
    return whole.unionByName(empty).unionByName(nameless.select(nobody.alias("doc_id"), F.size("s").cast("long").alias("n_shingles"), nobody.alias("component_id")))


def drop_near_duplicates(docs: DataFrame, k: int = 5, threshold: tuple[int, int] = (80, 100)) -> DataFrame:
    """The documents without those that link, directly or not, with one of a smaller doc_id; one row of each doc_id stays.

    Rows without doc_id stay. The ids that go are broadcast up to a checked count, and joined beyond it.
    """
    found = materialise(jaccard_components(docs, k, threshold))
    gone = found.filter("doc_id != component_id").select("doc_id").distinct()
    counts = found.agg(F.count("doc_id").alias("all"), F.countDistinct("doc_id").alias("ids")).first()
    kept = docs.join(F.broadcast(gone) if gone.count() <= BROADCAST_IDS else gone, "doc_id", "left_anti").select(docs.columns)
    if counts["all"] == counts["ids"]:
        return kept
    return kept.filter("doc_id IS NOT NULL").dropDuplicates(["doc_id"]).unionByName(kept.filter("doc_id IS NULL"))


def _remaining(comparer: _Comparer, shared: DataFrame, members: DataFrame, seen: DataFrame, labels: DataFrame, keep: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Pairs (u, v) of nodes in two components that share a bucket, may link, and have not been compared."""
    known = members.join(labels.withColumnRenamed("component", "known"), "node", "left").withColumn("component", F.coalesce("known", "node")).drop("known")
    known = materialise(known.select("node", "leader", "component"))
    state = known.groupBy("leader").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("nodes"))
    posts = shared.select("token", F.col("node").alias("leader"), "n", "at", (F.col("node") == F.col("pivot")).alias("lead")).join(state.withColumn("leader", F.col("leader") + F.lit(0)), "leader")
    # Of each bucket: its largest component, and whether there are two. All have met a pivot that is alone in its group, if they are, too.
    held = posts.groupBy("token", "low", "high").agg(F.count("*").alias("c"), F.sum(F.col("lead").cast("int")).alias("leads"), F.max("nodes").alias("nodes"))
    pure = F.col("low") == F.col("high")
    mixed = held.groupBy("token").agg(F.max(F.when(pure, F.struct("c", "low"))).alias("top"), F.count("*").alias("all"), F.count(F.when(F.col("c") > F.col("leads"), 1)).alias("others"), F.max(~pure).alias("odd"), F.max("nodes").alias("most"))
    mixed = mixed.filter("odd OR CASE WHEN most > 1 THEN all ELSE others END > 1")
    posts = posts.join(mixed.select(_anew("token"), F.col("top.low").alias("top"), "most"), "token").filter("NOT lead OR most > 1")
    # Sets of sizes that can link lie in one step of this scale, or in neighbouring ones.
    ratio = comparer.denominator / comparer.numerator
    step = F.floor(F.log(F.col("n").cast("double")) / math.log(ratio + 1e-9)) if ratio > 1 else F.col("n").cast("long")
    posts = keep(posts.select("token", "leader", "n", "at", "low", "high", step.alias("step"), (~pure | (F.col("low") != F.coalesce("top", F.lit(-1)))).alias("minor")))
    few = posts.filter("minor").withColumn("step", F.explode(F.array(F.col("step") - 1, F.col("step"), F.col("step") + 1)))
    few = few.select("token", "step", *(F.col(c).alias(f"{c}2") for c in ("leader", "n", "at", "low", "high")))
    once = ~F.col("minor") | (F.col("leader") < F.col("leader2"))
    one = pure & (F.col("low") == F.col("low2")) & (F.col("low2") == F.col("high2"))
    met = posts.join(few, ["token", "step"]).filter((F.col("leader") != F.col("leader2")) & once & ~one & comparer.may_meet("n", "at", "n2", "at2"))
    pairs = met.select(F.least("leader", "leader2").alias("a"), F.greatest("leader", "leader2").alias("b")).distinct()
    # Expand the groups: across pairs, and within groups that hold two components.
    odd = state.filter("low != high").select("leader")
    pairs = pairs.unionByName(odd.select(F.col("leader").alias("a"), F.col("leader").alias("b")))
    side = known.select("leader", "node", "component")
    expanded = pairs.join(side.toDF("a", "x", "kx"), "a").join(side.toDF("b", "y", "ky"), "b").filter("kx != ky")
    return materialise(expanded.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v")).distinct().join(seen, ["u", "v"], "left_anti"))

"""Best-fit packing of token sequences after Martello-Toth dominance reduction.

Only the histogram of piece lengths decides a packing: at most `capacity` distinct lengths, whatever the number of
documents. The reduction fixes bins that provably dominate every other bin of their largest piece and takes them out of
the instance; best-fit decreasing packs the remainder, a run of equal bins at a time. Each piece then finds its place from
its rank among the pieces of its length, which is counted in two levels, so a hot length is not sorted by one task.

Null texts count as empty, and an empty document is its end token alone. An empty table gives an empty result.
"""

from __future__ import annotations

import base64
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fuzzyfeat.session import materialise, prepare

CAPACITY, END_ID, RANKED_TOGETHER, SALTS_TOGETHER = 1024, 2, 1024, 4096


@lru_cache(maxsize=2)
def encoder(vocabulary: str):
    """text -> ids as the tokenizer file gives them by default. The rank file beside it gives the same ids several times faster; texts that hold a special token, or that it can't take, go to the full tokenizer."""
    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb"))}
    quick = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    full = Tokenizer.from_file(public_tokenizers.path(f"{vocabulary}.json"))
    special = [token.content for token in full.get_added_tokens_decoder().values()]

    def encode(text: str) -> list[int]:
        if not any(token in text for token in special):
            try:
                return quick.encode_ordinary(text)
            except BaseException as error:  # the library's panics are no Exception
                if isinstance(error, KeyboardInterrupt | SystemExit | MemoryError):
                    raise
        return full.encode(text, add_special_tokens=False).ids

    return encode


def token_pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str = "byte_bpe_50k", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, piece, start, length, ids): ids little-endian unsigned 32-bit. Only documents over `capacity` are cut, and only their first piece is shorter."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                rows, numbers, starts, lengths, pieces = [], [], [], [], []
                for row, text in enumerate(part.column(1)):
                    ids = encode(text.as_py() or "")
                    ids.append(end_id)
                    raw = np.array(ids, "<u4").tobytes()
                    cuts = [0, *range(len(ids) % capacity or capacity, len(ids) + 1, capacity)]
                    for number, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                        rows.append(row)
                        numbers.append(number)
                        starts.append(a)
                        lengths.append(b - a)
                        pieces.append(raw[4 * a : 4 * b])
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).take(pa.array(rows, pa.int64())), pa.array(numbers, pa.int32()), pa.array(starts, pa.int64()), pa.array(lengths, pa.int64()), pa.array(pieces, pa.binary())],
                    ["doc_id", "piece", "start", "length", "ids"],
                )

    prepare(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(work, "doc_id long, piece int, start long, length long, ids binary")


def _fitting(lengths: list[int], room: int) -> int:
    """Index of the largest length of at most `room`, or -1."""
    return bisect_left(lengths, room + 1) - 1


def reduce_by_dominance(counts: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Fix dominating bins, take their pieces out of `counts`, and return [(lengths in the bin, how many such bins)].

    For a piece L with room r = capacity - L, the bin {L} dominates if nothing fits beside L; {L, j} with the largest j <= r
    does if j = r, if no two pieces fit beside L, or if no three fit and j is at least the fullest fitting pair.
    """
    fixed: list[tuple[dict[int, int], int]] = []

    def take(bin_: dict[int, int], times: int) -> None:
        fixed.append((bin_, times))
        for length, q in bin_.items():
            counts[length] -= q * times
            if not counts[length]:
                del counts[length]

    for large in sorted(counts, reverse=True):
        while counts.get(large):
            room = capacity - large
            others = sorted(x for x in counts if x != large or counts[x] > 1)
            at = _fitting(others, room)
            if at < 0:
                take({large: 1}, counts[large])
                break
            best = others[at]
            stock = [x for x in sorted(counts) for _ in range(min(3, counts[x] - (x == large)))][:3]
            if best < room and len(stock) > 1 and sum(stock[:2]) <= room:
                if len(stock) > 2 and sum(stock) <= room:
                    break
                pair = max((a + b for i, a in enumerate(others) for b in [others[_fitting(others, room - a)]] if _fitting(others, room - a) >= 0 and a + b <= room), default=0)
                if best < pair:
                    break
            if best == large:
                take({large: 2}, counts[large] // 2)
            else:
                # the conditions hold while both lengths last and no smaller stock appears: stock only shrinks
                take({large: 1, best: 1}, min(counts[large], counts[best]))
    return fixed


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Best-fit decreasing over a histogram: equal bins are kept as one group, and a step fills as many of them as it can."""
    groups: dict[int, list[tuple[dict[int, int], int]]] = {}
    rooms: list[int] = []

    def put(room: int, bin_: dict[int, int], times: int) -> None:
        if times:
            if room not in groups:
                groups[room] = []
                insort(rooms, room)
            groups[room].append((bin_, times))

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            at = bisect_left(rooms, length)
            room = rooms[at] if at < len(rooms) else capacity
            bin_, times = groups[room].pop() if at < len(rooms) else ({}, left)
            if at < len(rooms) and not groups[room]:
                del groups[room]
                rooms.pop(at)
            each = room // length
            whole = min(times, left // each)
            put(room - each * length, {**bin_, length: each}, whole)
            left -= whole * each
            rest = times - whole
            if left and rest and left < each:
                put(room - left * length, {**bin_, length: left}, 1)
                left, rest = 0, rest - 1
            if bin_:
                put(room, bin_, rest)
    return [x for room in rooms for x in groups[room]]


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[dict[int, int], int]]:
    """[(lengths in the bin, how many such bins)] for a histogram of lengths: the dominating bins first."""
    counts = {k: v for k, v in counts.items() if v}
    fixed = reduce_by_dominance(counts, capacity)
    return fixed + best_fit_decreasing(counts, capacity)


def places(bins: list[tuple[dict[int, int], int]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, end rank, first sequence, pieces a sequence, offset) for each length of each group of bins."""
    out, used, sequence = [], {}, 0
    for bin_, times in bins:
        offset = 0
        for length, q in bin_.items():
            first = used.get(length, 0)
            used[length] = first + q * times
            out.append((length, first, first + q * times, sequence, q, offset))
            offset += q * length
        sequence += times
    return out


def salt_offsets(held: DataFrame, together: int = SALTS_TOGETHER) -> DataFrame:
    """(length, __salt, __before): pieces of the length in smaller salts, from their counts, in two levels: no task holds all salts of a hot length."""
    held = held.withColumn("__range", F.floor(F.col("__salt") / together))
    earlier = lambda order, *by: F.coalesce(F.sum("count").over(Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranges = held.groupBy("length", "__range").agg(F.sum("count").alias("count")).withColumn("__base", earlier("__range", "length"))
    inside = held.withColumn("__inside", earlier("__salt", "length", "__range"))
    ranges = ranges.select((F.col("length") + F.lit(0)).alias("length"), "__range", "__base")
    return inside.join(ranges, ["length", "__range"]).select("length", "__salt", (F.col("__inside") + F.col("__base")).alias("__before"))


def assign(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """The pieces (doc_id, piece, length and any other columns) with sequence_id and offset. Reads `pieces` twice: give it a written table."""
    spark = pieces.sparkSession
    total = pieces.groupBy("length").count().collect()  # at most `capacity` rows
    counts = {row["length"]: row["count"] for row in total}
    rows = places(plan(counts, capacity))
    salts = max(1, sum(counts.values()) // RANKED_TOGETHER)
    salted = pieces.withColumn("__salt", F.pmod(F.xxhash64("doc_id", "piece", "start"), F.lit(salts)))
    ranked = salted.withColumn("__rank", F.row_number().over(Window.partitionBy("length", "__salt").orderBy("doc_id", "piece")) - 1)
    before = salt_offsets(salted.groupBy("length", "__salt").count())
    ranked = ranked.join(before.select((F.col("length") + F.lit(0)).alias("length"), "__salt", "__before"), ["length", "__salt"]).withColumn("__rank", F.col("__rank") + F.col("__before")).drop("__before", "__salt")
    if len(rows) > 256 * capacity:
        raise RuntimeError("more groups of bins than a packing of this capacity can have")
    found = spark.createDataFrame(rows, "length long, __from long, __to long, __sequence long, __each long, __offset long")
    met = ranked.join(F.broadcast(found), (ranked["length"] == found["length"]) & (F.col("__rank") >= F.col("__from")) & (F.col("__rank") < F.col("__to"))).drop(found["length"])
    step = F.col("__rank") - F.col("__from")
    return met.withColumn("sequence_id", F.col("__sequence") + F.floor(step / F.col("__each"))).withColumn("offset", F.col("__offset") + F.pmod(step, F.col("__each")) * F.col("length")).drop("__rank", "__from", "__to", "__sequence", "__each", "__offset")


def pack(docs: DataFrame, capacity: int = CAPACITY, **options) -> DataFrame:
    """Documents to pieces with their ids, sequence and offset."""
    return assign(materialise(token_pieces(docs, capacity, **options)), capacity)

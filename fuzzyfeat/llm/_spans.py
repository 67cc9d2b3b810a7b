"""Spans found in texts: how an operator returns them, and the digests that queries derive."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

SPANS = "array<struct<kind:string,start:int,end:int,base:boolean,score:double>>"
ARROW = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("base", pa.bool_()), ("score", pa.float64())]))


def batch(ids, spans: list[list[tuple]]) -> pa.RecordBatch:
    """(doc_id, spans) from (kind, start, end, base, score) tuples; offsets are code points, ends exclusive."""
    names = ("kind", "start", "end", "base", "score")
    return pa.RecordBatch.from_arrays([ids, pa.array([[dict(zip(names, s, strict=True)) for s in x] for x in spans], ARROW)], ["doc_id", "spans"])


def joined(spans: str | Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])))


def digests(kinds: tuple[str, ...]) -> list[Column]:
    """n_<kind> of the base spans, base_sha256 and spans."""
    base = F.filter("spans", lambda s: s["base"])
    of_kind = lambda k: F.size(F.filter(base, lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    counts = [of_kind(k) for k in kinds]
    return [*counts, F.sha2(joined(base), 256).alias("base_sha256"), joined("spans").alias("spans")]

"""What a feature is: the mixed distance, the learners and the selectors dispatch on its kind."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import types as T


@dataclass(frozen=True)
class Feature:
    name: str
    kind: str  # continuous, ordinal (ranks from 0) or symbolic
    levels: int = 0  # of an ordinal feature

    @property
    def numeric(self) -> bool:
        return self.kind != "symbolic"


def infer(df: DataFrame, skip: tuple[str, ...] = ("row_id", "label", "fine_label")) -> list[Feature]:
    """Kinds proposed from the Spark types: strings and booleans are symbolic, all other scalars continuous."""
    return [Feature(f.name, "symbolic" if isinstance(f.dataType, T.StringType | T.BooleanType) else "continuous") for f in df.schema.fields if f.name not in skip]

"""Token and character positions of utterances (half-open ranges)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def attach(utts: DataFrame, sizes: dict | None = None) -> DataFrame:
    """utts with `<unit>_start` and `<unit>_end` for each unit of sizes (default: words `tok` and characters `char`).

    A sub-word unit is one more entry, as {"sub": F.size("pieces")}. One shuffle by meeting serves all units."""
    sizes = sizes or {"tok": F.col("n_tok"), "char": F.length("text")}
    order = Window.partitionBy("meeting_id").orderBy("utt_no").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    utts = utts.withColumns({f"{unit}_end": F.sum(size.cast("long")).over(order) for unit, size in sizes.items()})  # one window for all units
    return utts.withColumns({f"{unit}_start": F.col(f"{unit}_end") - size.cast("long") for unit, size in sizes.items()})

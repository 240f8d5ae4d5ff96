"""The dynamic run with the gold backbone, joined to each meeting instead of broadcast."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.backbones import GoldBackbone
from ..operators.runs import Meeting, arrays, steps_of


def gold_steps(nested: DataFrame, segments: DataFrame, k: int) -> DataFrame:
    """(meeting_id, step, boundary_utt): a window from each boundary on, until the last gold segment; segments longer than k are held at the window's end and go on."""
    segs = segments.groupBy("meeting_id").agg(F.sort_array(F.collect_list(F.struct("seg_start", "seg_end"))).alias("segs"))

    def run(batches):
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                ends = {int(s["seg_end"]) for s in r.segs}
                backbone = GoldBackbone({r.meeting_id: [(int(s["seg_start"]), int(s["seg_end"]), "") for s in r.segs]})
                step = 0
                for s in steps_of(Meeting(r), backbone, k, "after", "boundary"):
                    if s[7] in ends:  # else a window's end inside a long segment, or the tail behind the last one
                        out.append((r.meeting_id, step, s[7]))
                        step += 1
            yield pd.DataFrame(out, columns=["meeting_id", "step", "boundary_utt"])

    return arrays(nested).join(segs, "meeting_id").mapInPandas(run, "meeting_id string, step long, boundary_utt long")

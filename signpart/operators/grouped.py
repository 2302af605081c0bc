"""Many small graphs side by side, without a pandas call for each."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame


def labels_per_group(rows: DataFrame, columns: list[str], solve: Callable[..., dict[int, int]]) -> DataFrame:
    """(g, v, cluster) of rows with column g and ``columns``; solve(*arrays) gives the labels of one group.

    Rows are dealt by g and sorted, and a task cuts them at the groups as they
    stream past: memory holds a batch and the largest group.
    """
    dealt = rows.select("g", *columns).repartition("g").sortWithinPartitions("g")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: pd.DataFrame | None = None

        def solved(frame: pd.DataFrame, whole: bool) -> tuple[pd.DataFrame, pd.DataFrame]:
            """(labels of the complete groups, rows of the last one unless the input ends)."""
            keys = frame["g"].to_numpy()
            cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
            ends = list(zip(cuts, cuts[1:])) if whole else list(zip(cuts[:-1], cuts[1:-1]))
            arrays = [frame[c].to_numpy() for c in columns]
            g, v, cluster = [], [], []
            for a, b in ends:
                found = solve(*(x[a:b] for x in arrays))
                g += [keys[a]] * len(found)
                v += found.keys()
                cluster += found.values()
            made = pd.DataFrame({"g": g, "v": v, "cluster": cluster}, dtype="int64")
            return made, frame.iloc[cuts[-2] :] if not whole else frame.iloc[:0]

        for frame in frames:
            if len(frame):
                made, held = solved(frame if held is None or not len(held) else pd.concat([held, frame]), False)
                if len(made):
                    yield made
        if held is not None and len(held):
            yield solved(held, True)[0]

    return dealt.mapInPandas(run, "g long, v long, cluster long")

"""Groups of rows as a stream: for many small groups, without a frame's overhead each."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd


def grouped(frames: Iterator[pd.DataFrame], keys: Sequence[str], each: Callable[[pd.DataFrame], pd.DataFrame | None]) -> Iterator[pd.DataFrame]:
    """each(group) over the whole groups of frames that are sorted by keys; a group may span frames."""
    open_ = None
    for frame in frames:
        if open_ is not None:
            frame = pd.concat([open_, frame], ignore_index=True)
        if not len(frame):
            continue
        change = np.zeros(len(frame) - 1, bool)
        for k in keys:
            v = frame[k].to_numpy()
            change |= v[1:] != v[:-1]
        cuts = [0, *(np.flatnonzero(change) + 1).tolist()]
        out = [r for a, b in zip(cuts, cuts[1:], strict=False) if (r := each(frame.iloc[a:b])) is not None]
        open_ = frame.iloc[cuts[-1] :]
        if out:
            yield pd.concat(out, ignore_index=True)
    if open_ is not None and len(open_) and (r := each(open_)) is not None:
        yield r

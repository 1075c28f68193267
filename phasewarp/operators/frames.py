"""Frames that leave pandas functions."""

from __future__ import annotations

import pandas as pd


def plain(frame: pd.DataFrame) -> pd.DataFrame:
    """Text columns as plain objects: joined or empty text columns are otherwise held in chunks,
    which the exchange with the JVM does not take."""
    for name in frame.columns:
        if not pd.api.types.is_numeric_dtype(frame[name].dtype):
            frame[name] = frame[name].astype(object)
    return frame

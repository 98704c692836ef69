"""Plain pandas functions that queries ship to Python workers."""

from __future__ import annotations

import pandas as pd


def reversed_text(x: pd.Series) -> pd.Series:
    return x.str[::-1]


def gap_to_best(frame: pd.DataFrame) -> pd.DataFrame:
    return frame.assign(gap=(frame["s_acctbal"] - frame["s_acctbal"].max()).round(2))[["s_suppkey", "gap"]]

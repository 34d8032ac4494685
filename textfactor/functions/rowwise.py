"""Row-wise application inside pandas functions. In a module of its own: workers import it, and must not define SQL functions while they do."""

from __future__ import annotations

import pandas as pd


def each(function, *columns) -> pd.Series:
    """function of every row's values; null where one of them is null."""
    return pd.Series([None if any(v is None for v in row) else function(*row) for row in zip(*columns, strict=True)], dtype=object)

def same_rows(mine, other) -> str:
    """'' if both pandas frames hold the same rows under the same column names, else what differs."""
    a, b = mine[sorted(mine.columns)], other[sorted(other.columns)]
    if list(a.columns) != list(b.columns):
        return f"columns {list(a.columns)} and {list(b.columns)}"
    if len(a) != len(b):
        return f"{len(a)} and {len(b)} rows"
    a, b = (x.sort_values(list(x.columns)).reset_index(drop=True) for x in (a, b))
    bad = [c for c in a.columns if not ((a[c] == b[c]) | (a[c].isna() & b[c].isna())).all()]
    return f"columns {bad} differ" if bad else ""

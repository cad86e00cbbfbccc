"""Query results as comparable rows."""

import pandas as pd


def _cell(v):
    if pd.api.types.is_scalar(v) and pd.isna(v):
        return "NULL"
    if isinstance(v, bool) or str(v) in ("True", "False"):
        return str(bool(v))
    return f"{float(v):.8g}" if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)


def rows_of(pdf):
    """Rows of a pandas frame as comparable text, columns by name."""
    return sorted(tuple(_cell(v) for v in r) for r in pdf[sorted(pdf.columns)].astype(object).itertuples(index=False))

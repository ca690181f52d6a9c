import pandas as pd


def normal(df: pd.DataFrame) -> list[tuple]:
    """Rows in a fixed order, values in one form."""

    def one(v):
        if v is None or v is pd.NaT or v is pd.NA or isinstance(v, float) and v != v:
            return None
        return str(v) if isinstance(v, (str, bool, pd.Timestamp)) or type(v).__name__ == "bool_" else float(v) if hasattr(v, "__float__") else str(v)

    return sorted((tuple(map(one, r)) for r in df[sorted(df.columns)].itertuples(index=False)), key=repr)

"""Written tables in the folder that all executors share."""

from __future__ import annotations

from pyspark.sql import DataFrame

from fpfilter.sources.tables import shared_dir, written

__all__ = ["fresh", "shared_dir", "written"]


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like these that ``df`` does not have, in any case of letters."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        out.append(name)
    return out

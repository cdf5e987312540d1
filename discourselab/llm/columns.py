"""Names for internal columns that no column of a user's table has."""

from __future__ import annotations

from pyspark.sql import DataFrame


def unused(table: DataFrame, *names: str) -> list[str]:
    """The names, each with as many underscores in front as it takes to be new to ``table``."""
    held, out = {x.lower() for x in table.columns}, []
    for name in names:
        while name.lower() in held:
            name = f"_{name}"
        held.add(name.lower())
        out.append(name)
    return out

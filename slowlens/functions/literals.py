"""Long constant arrays and maps as one parsed expression: one call to the JVM instead of one for each element."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _text(v: object) -> str:
    if isinstance(v, bool):
        return str(v).lower()
    if isinstance(v, int):
        return str(v)
    if isinstance(v, float):
        return f"double('{v!r}')"
    if isinstance(v, str):
        return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(v, (list, tuple)):
        return f"array({', '.join(map(_text, v))})"
    raise TypeError(f"no literal for {type(v)}")


def constant(values: list, kind: str) -> Column:
    """`values` as a constant of the SQL type `kind`."""
    return F.expr(f"CAST({_text(values)} AS {kind})")


def token_lookup(known: dict[str, list[tuple[int, int]]]) -> Column:
    """token -> array of (c, i) as a constant map."""
    entries = [f"{_text(t)}, array({', '.join(f'named_struct({chr(39)}c{chr(39)}, {c}, {chr(39)}i{chr(39)}, {i})' for c, i in v)})" for t, v in known.items()]
    return F.expr(f"map({', '.join(entries)})")

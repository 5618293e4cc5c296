"""Arrow types of id columns, and names that no column of the user's has."""

from __future__ import annotations

from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type


def arrow_kind(kind: T.DataType) -> pa.DataType:
    """The Arrow type in which Spark hands over and takes back a column of this type."""
    return to_arrow_type(kind)


def unused(columns: Iterable[str], *names: str) -> list[str]:
    """The names, with underscores put before each until it is none of the columns (case is not told apart)."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out

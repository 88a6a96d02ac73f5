"""Arrays of literals, parsed in one call rather than built element by element."""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import Column
from pyspark.sql import functions as F


def int_array(values: Iterable[int]) -> Column:
    return F.expr(f"array({', '.join(f'{int(v)}L' for v in values)})")


def double_array(values: Iterable[float]) -> Column:
    def one(v: float) -> str:
        return f"{v!r}D" if math.isfinite(v) else f"double('{v}')"

    return F.expr(f"array({', '.join(one(float(v)) for v in values)})")

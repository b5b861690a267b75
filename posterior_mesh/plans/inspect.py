"""What a physical plan does: counts of its operators, for tests and reports."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def operators(df: DataFrame) -> Counter:
    text = df._jdf.queryExecution().executedPlan().toString()
    return Counter(re.findall(r"(?m)^[\s:+*\-()\d]*([A-Z]\w+)", text))

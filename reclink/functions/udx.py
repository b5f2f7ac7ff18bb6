"""User-defined functions, for what built-ins cannot express; Arrow batches throughout."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, Row, StringType, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult


def jaro(x: str, y: str) -> float:
    if x == y:
        return 1.0
    n, m = len(x), len(y)
    if not n or not m:
        return 0.0
    reach = max(n, m) // 2 - 1
    used, mine = [False] * m, []
    for i, c in enumerate(x):
        for j in range(max(0, i - reach), min(m, i + reach + 1)):
            if not used[j] and y[j] == c:
                used[j] = True
                mine.append(c)
                break
    if not mine:
        return 0.0
    other = [c for c, u in zip(y, used) if u]
    k = len(mine)
    swaps = sum(a != b for a, b in zip(mine, other)) // 2
    return (k / n + k / m + (k - swaps) / k) / 3


def jaro_winkler(x: str, y: str, scale: float = 0.1, boost: float = 0.7) -> float:
    """Jaro similarity, raised by the common prefix (up to four signs) from `boost` on."""
    base = jaro(x, y)
    if base <= boost:
        return base
    shared = next((i for i in range(min(4, len(x), len(y))) if x[i] != y[i]), min(4, len(x), len(y)))
    return base + shared * scale * (1 - base)


@F.pandas_udf(DoubleType())
def jaro_winkler_udf(x: pd.Series, y: pd.Series) -> pd.Series:
    return pd.Series([None if a is None or b is None else jaro_winkler(a, b) for a, b in zip(x, y)], dtype="float64")


@F.pandas_udf(IntegerType())
def words_udf(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for texts in batches:
        yield texts.str.split().str.len().astype("int32")


@F.pandas_udf(DoubleType())
def gini_udaf(values: pd.Series) -> float:
    """Gini impurity of the present values over all rows of the group."""
    share = values.value_counts() / max(1, len(values))
    return float((share * (1 - share)).sum())


@F.udtf(returnType=StructType().add("combo_id", IntegerType()).add("sig", StringType()))
class SignatureRows:
    """combo_id, sig for each pair of a record's given values; missing values give none."""

    def eval(self, given: str, family: str, street: str):
        values = [given, family, street]
        for k, (i, j) in enumerate(((0, 1), (0, 2), (1, 2)), 1):
            if values[i] is not None and values[j] is not None:
                yield k, f"{values[i]}|{values[j]}"


@F.udtf(returnType=StructType().add("gram", StringType()))
class QGrams:
    def eval(self, text: str, q: int):
        if text is not None:
            for i in range(max(1, len(text) - q + 1)):
                yield (text[i : i + q],)


@F.udtf
class CombinationRows:
    """Signatures of any table's records, for combinations given as text ("given,family;street").
    The key keeps its type; names that the table lacks are refused when the query is planned."""

    @staticmethod
    def analyze(rows: AnalyzeArgument, key: AnalyzeArgument, combos: AnalyzeArgument) -> AnalyzeResult:
        if not rows.isTable or not key.isConstantExpression or not combos.isConstantExpression:
            raise ValueError("a table, the name of its key and the combinations are needed")
        asked = [key.value, *(a for combo in combos.value.split(";") for a in combo.split(","))]
        missing = sorted(set(asked) - set(rows.dataType.fieldNames()))
        if missing:
            raise ValueError(f"the table has no column {', '.join(missing)}")
        return AnalyzeResult(StructType().add(key.value, rows.dataType[key.value].dataType).add("combo_id", IntegerType()).add("sig", StringType()))

    def eval(self, rows: Row, key: str, combos: str):
        for k, combo in enumerate(combos.split(";"), 1):
            values = [rows[a] for a in combo.split(",")]
            if None not in values:
                yield rows[key], k, "|".join(map(str, values))

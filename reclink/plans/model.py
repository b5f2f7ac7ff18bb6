"""What a linkage is made of: attributes, combinations and relation rules."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from reclink.functions.text import whole


@dataclass(frozen=True)
class Qid:
    """A quasi-identifying attribute and the function that makes its token."""

    name: str
    fn: Callable[[Column], Column] = whole

    def token(self) -> Column:
        return self.fn(F.col(self.name))


@dataclass(frozen=True)
class Combo:
    """An ordered attribute combination with its scores."""

    combo_id: int
    attrs: tuple[str, ...]
    s_c: float = 0.0
    s_g: float = 0.0
    score: float = 0.0


@dataclass(frozen=True)
class Rule:
    """A relation: records of one database with equal, complete keys are related.

    kind is equal, conj, overlap (an array column; with max_df, elements in more records are
    no relation), group or group_role.
    """

    kind: str
    columns: tuple[str, ...]
    role: str | None = None
    max_df: int | None = None
    fn: Callable[[Column], Column] = whole

    @staticmethod
    def equal(column: str, fn: Callable[[Column], Column] = whole) -> Rule:
        return Rule("equal", (column,), fn=fn)

    @staticmethod
    def conj(columns: Sequence[str]) -> Rule:
        return Rule("conj", tuple(columns))

    @staticmethod
    def overlap(column: str, max_df: int | None = None) -> Rule:
        return Rule("overlap", (column,), max_df=max_df)

    @staticmethod
    def group(column: str) -> Rule:
        return Rule("group", (column,))

    @staticmethod
    def group_role(column: str, role: str) -> Rule:
        return Rule("group_role", (column,), role=role)


@dataclass(frozen=True)
class Settings:
    """Parameters of a linkage."""

    alpha: float = 0.5
    c_t: float = 0.7
    n_a: int = 5
    lam: float = 1.2
    mu: float = 0.2
    p_t: float = 0.5
    beta: float = 0.5
    s_t: float = 0.8
    sim_a: str = "jaccard"
    sim_r: str = "jaccard"
    prob_mode: str = "literal"
    count_scope: str = "per_db"
    features: tuple[str, ...] = field(default=("nbr_sigs",))

    def __post_init__(self):
        for name in ("alpha", "c_t", "p_t", "beta", "s_t"):
            if not 0 <= getattr(self, name) <= 1:
                raise ValueError(f"{name} must lie in [0, 1]")
        if self.lam <= 1 or not 0 < self.mu < 1:
            raise ValueError("lam must exceed 1 and mu lie in (0, 1)")
        if self.n_a < 1:
            raise ValueError("n_a must be at least 1")


def check_columns(schema: StructType, qids: Sequence[Qid]) -> None:
    missing = [q.name for q in qids if q.name not in schema.names]
    if missing:
        raise ValueError(f"no such columns: {missing}")

"""What a release is about: quasi-identifiers, sensitive column, key and weights."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from gainbound.plans.hierarchy import Hierarchy

NUMERIC, CATEGORICAL = "numeric", "categorical"
_INTEGRAL = ("tinyint", "smallint", "int", "bigint")


@dataclass(frozen=True)
class Attribute:
    """A quasi-identifier. Numeric ones are integers (scale or number others first); categorical ones have a hierarchy."""

    name: str
    kind: str = NUMERIC
    hierarchy: Hierarchy | None = None

    def __post_init__(self):
        if (self.kind == CATEGORICAL) != (self.hierarchy is not None) or self.kind not in (NUMERIC, CATEGORICAL):
            raise ValueError(f"{self.name}: a categorical attribute, and no other, has a hierarchy")


@dataclass(frozen=True)
class ReleaseSpec:
    qi: tuple[Attribute, ...]
    sa: str
    key: str
    weights: tuple[float, ...] = field(default=())

    def __post_init__(self):
        if not self.qi:
            raise ValueError("a release needs a quasi-identifier")
        if not self.weights:
            object.__setattr__(self, "weights", tuple([1.0 / len(self.qi)] * len(self.qi)))
        if len(self.weights) != len(self.qi) or abs(sum(self.weights) - 1) > 1e-9:
            raise ValueError("weights must be as many as the attributes and sum to 1")

    def validate(self, df: DataFrame) -> None:
        kinds = dict(df.dtypes)
        for c in (*(a.name for a in self.qi), self.sa, self.key):
            if c not in kinds:
                raise ValueError(f"no column {c}")
        for a in self.qi:
            if a.kind == NUMERIC and kinds[a.name] not in _INTEGRAL:
                raise ValueError(f"{a.name} is numeric but {kinds[a.name]}; scale it to an integer")

    def with_qi(self, n: int) -> ReleaseSpec:
        """The first n quasi-identifiers, with even weights."""
        return replace(self, qi=self.qi[:n], weights=())

    def with_sa(self, sa: str) -> ReleaseSpec:
        return replace(self, sa=sa)

    @property
    def axes(self) -> list[str]:
        """Names of the encoded coordinates."""
        return [f"x{i + 1}" for i in range(len(self.qi))]

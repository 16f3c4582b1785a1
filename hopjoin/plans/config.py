"""User-settable parameters of the discovery."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame

#: The token -> concept map of the test bed.
LEXICON = {
    "medication": "drug", "item": "part", "product": "part", "hospital": "clinic",
    "territory": "place", "client": "customer", "resident": "person",
}


def _default_embedder():
    from hopjoin.functions.names import LexiconEmbedder

    return LexiconEmbedder(LEXICON)


@dataclass(frozen=True)
class TableRef:
    """A table of a database."""

    db: str
    table: str
    df: DataFrame

    @property
    def node(self) -> str:
        return f"{self.db}.{self.table}"


@dataclass(frozen=True)
class DiscoveryConfig:
    alpha: float = 0.4
    beta: float = 0.4
    gamma: float = 0.2
    name_threshold: float = 0.6
    value_threshold: float = 0.5
    epsilon: float = 1e-9
    log_base: float = 2.0
    overlap: str = "exact"
    direction: str = "left"
    scope: str = "cross"
    assignment: str = "best"
    min_score: float = 0.5
    embedder: Any = field(default_factory=_default_embedder)
    semantic_mode: str = "clip"
    token_kind: str = "jaccard"
    normalize: str | None = None
    blocking: bool = False
    cast_to_string: bool = False
    kinds: tuple[str, ...] = ("fk", "fuzzy")
    #: columns with a longer value are compared by equality
    long_text: int = 256

    def __post_init__(self):
        weights = (self.alpha, self.beta, self.gamma)
        if min(weights) < 0 or abs(sum(weights) - 1) > 1e-9:
            raise ValueError("alpha, beta and gamma must not be negative and must sum to 1")
        for name, allowed in (("overlap", ("exact", "fuzzy", "value_score")), ("direction", ("left", "right", "min", "max", "mean")), ("scope", ("cross", "all")), ("assignment", ("best", "mutual", "one_to_one"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

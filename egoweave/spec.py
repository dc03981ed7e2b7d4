"""What a user states: which subgraphs, how to pack them, how to run programs on them."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class NeighborhoodSpec:
    """One subgraph per seed: the ball of radius k around it."""

    seed_pred: str | None = None
    k: int = 1
    v_pred: str | None = None
    e_pred: str | None = None
    attrs_v: tuple[str, ...] = ()
    attrs_e: tuple[str, ...] = ()
    direction: str = "out"
    filter_mode: str = "pre"
    keep_center: bool = True

    def __post_init__(self):
        if self.k < 1 or self.direction not in ("out", "in", "both") or self.filter_mode not in ("pre", "post"):
            raise ValueError(f"not a neighbourhood: {self}")


@dataclass(frozen=True)
class AttributeSpec:
    """One subgraph per value of a vertex attribute."""

    column: str


@dataclass(frozen=True)
class PairSpec:
    """One subgraph per pair: union or intersection of two neighbourhoods."""

    pairs: DataFrame
    k: int = 1
    op: str = "union"


@dataclass(frozen=True)
class ListSpec:
    """Given vertex lists (sg_id, v)."""

    members: DataFrame


@dataclass(frozen=True)
class PackOptions:
    capacity: int = 90
    max_items: int | None = None
    order: str = "sketch"
    algorithm: str = "greedy"
    n_hashes: int = 6
    #: 0: one where the members are few, else as many as keep a task's members bounded
    n_buckets: int = 0
    #: how many values of the signature say where a subgraph goes
    key_hashes: int = 1
    weight_model: str = "unit"
    oversized: str = "solo"
    merge_fill: float = 0.5
    overlap: bool = True
    seed: int = 0


@dataclass(frozen=True)
class ExecOptions:
    mode: str = "vector"
    batch_size: int = 3000
    bitmap: str = "words"
    threads: int = 1
    sequential: bool = False
    form: str = "kernel"
    params: dict = field(default_factory=dict)


_CLAUSES = {"seed": "seed_pred", "hops": "k", "vertex": "v_pred", "edge": "e_pred", "direction": "direction", "mode": "filter_mode", "keep_center": "keep_center"}


def parse_spec(text: str) -> NeighborhoodSpec:
    """A spec from rule text such as ``seed p_size > 45; hops 2; edge weight > 5``."""
    spec = NeighborhoodSpec()
    for clause in filter(None, (c.strip() for c in text.split(";"))):
        word, _, rest = clause.partition(" ")
        if word not in _CLAUSES or not rest.strip():
            raise ValueError(f"unknown clause: {clause!r}")
        value: object = rest.strip()
        if word == "hops":
            if not re.fullmatch(r"\d+", str(value)):
                raise ValueError(f"hops takes a number: {clause!r}")
            value = int(str(value))
        elif word == "keep_center":
            value = str(value).lower() in ("true", "yes", "1")
        spec = replace(spec, **{_CLAUSES[word]: value})
    return spec

"""What a graph model is: entity types, relations with their operators, and how scores become a loss."""

from __future__ import annotations

import warnings
from dataclasses import dataclass, field, replace

OPERATORS = ("identity", "translation", "diagonal", "linear", "complex_diagonal", "circular_correlation")
SIMILARITIES = ("dot", "cos", "complex_dot")
LOSSES = ("ranking", "logistic", "softmax")


@dataclass(frozen=True)
class EntityType:
    """partitioned: split in P parts; otherwise whole, and shared by all tasks.

    featurised: a node is a bag of features, and the features' vectors are trained in its place; such a
    type is whole.
    """

    name: str
    partitioned: bool = True
    featurised: bool = False

    def __post_init__(self):
        if self.featurised and self.partitioned:
            object.__setattr__(self, "partitioned", False)


@dataclass(frozen=True)
class RelationSpec:
    """One relation. ``rhs_op`` transforms destinations (the default side), ``lhs_op`` sources.

    ``reciprocal``: one set of parameters for corrupted destinations and another for corrupted
    sources; then only the endpoint that stays is transformed.
    """

    name: str
    src_type: str
    dst_type: str
    lhs_op: str = "identity"
    rhs_op: str = "identity"
    weight: float = 1.0
    reciprocal: bool = False


@dataclass(frozen=True)
class GraphSpec:
    types: tuple[EntityType, ...]
    relations: tuple[RelationSpec, ...]
    dim: int = 32
    sim: str = "dot"
    loss: str = "softmax"
    margin: float = 0.1
    optimizer: str = "adagrad_row"
    lr: float = 0.1
    relation_lr: float = 0.01
    batch: int = 1000
    chunk: int = 50
    uniform: int = 50
    negatives: str = "batched"
    alpha: float = 0.5
    mask_known: bool = False
    n3: float = 0.0
    init_scale: float | None = None
    seed: int = 1

    def __post_init__(self):
        self.validate()

    def validate(self) -> None:
        names = [t.name for t in self.types]
        if len(set(names)) != len(names) or len({r.name for r in self.relations}) != len(self.relations):
            raise ValueError("names of types and of relations must be unique")
        for value, known, what in ((self.sim, SIMILARITIES, "similarity"), (self.loss, LOSSES, "loss"), (self.optimizer, ("sgd", "adagrad_row", "adagrad"), "optimizer"), (self.negatives, ("batched", "unbatched"), "negatives")):
            if value not in known:
                raise ValueError(f"unknown {what} {value!r}")
        for r in self.relations:
            if r.src_type not in names or r.dst_type not in names:
                raise ValueError(f"relation {r.name} has an unknown entity type")
            for op in (r.lhs_op, r.rhs_op):
                if op not in OPERATORS:
                    raise ValueError(f"unknown operator {op!r}")
                if op == "complex_diagonal" and self.dim % 2:
                    raise ValueError("complex vectors need an even dimension")
        if self.sim == "complex_dot" and self.dim % 2:
            raise ValueError("complex vectors need an even dimension")
        if not 0 <= self.alpha <= 1 or min(self.batch, self.chunk) < 1 or self.uniform < 0:
            raise ValueError("alpha, batch, chunk or uniform out of range")

    def type_no(self, name: str) -> int:
        return next(i for i, t in enumerate(self.types) if t.name == name)

    def relation_no(self, name: str) -> int:
        return next(i for i, r in enumerate(self.relations) if r.name == name)

    def op_size(self, op: str) -> int:
        return {"identity": 0, "translation": self.dim, "diagonal": self.dim, "linear": self.dim * self.dim, "complex_diagonal": self.dim, "circular_correlation": self.dim}[op]

    def n_shared(self, nodes: dict[str, int] | None = None) -> int:
        """Parameters that every task holds: relations, and the vectors of whole (unpartitioned) types."""
        rel = sum((self.op_size(r.lhs_op) + self.op_size(r.rhs_op)) * (2 if r.reciprocal else 1) for r in self.relations)
        return rel + sum((nodes or {}).get(t.name, 0) * self.dim for t in self.types if not t.partitioned)

    def scale(self) -> float:
        """Starting vectors are small: what training has not touched then scores near nothing."""
        return self.init_scale if self.init_scale is not None else 0.01

    def lint(self, edges: dict[str, int]) -> list[str]:
        """Relations whose operator has more parameters than the relation has edges."""
        out = [r.name for r in self.relations if "linear" in (r.lhs_op, r.rhs_op) and self.op_size("linear") > edges.get(r.name, 0)]
        for name in out:
            warnings.warn(f"linear operator of {name} has more parameters than edges", stacklevel=2)
        return out

    def with_(self, **changes) -> GraphSpec:
        return replace(self, **changes)


@dataclass(frozen=True)
class Preset:
    op: str
    sim: str
    loss: str = "softmax"
    reciprocal: bool = False
    n3: float = 0.0
    extra: dict = field(default_factory=dict)


#: Known models as operator and similarity.
PRESETS = {
    "rescal": Preset("linear", "dot"),
    "transe": Preset("translation", "cos", "ranking"),
    "distmult": Preset("diagonal", "dot"),
    "complex": Preset("complex_diagonal", "complex_dot"),
    "hole": Preset("circular_correlation", "dot", "logistic"),
    "starspace": Preset("identity", "cos", "ranking", extra={"negatives": "unbatched"}),
    "complex_n3_reciprocal": Preset("complex_diagonal", "complex_dot", reciprocal=True, n3=1e-3),
    "identity": Preset("identity", "dot"),
}


def preset(name: str, types, relations: list[tuple[str, str, str]], **changes) -> GraphSpec:
    """A spec in which all relations have a known model's operator."""
    p = PRESETS[name]
    rels = tuple(RelationSpec(r, s, d, rhs_op=p.op, lhs_op=p.op if p.reciprocal else "identity", reciprocal=p.reciprocal) for r, s, d in relations)
    return GraphSpec(tuple(types), rels, **{"sim": p.sim, "loss": p.loss, "n3": p.n3} | p.extra | changes)

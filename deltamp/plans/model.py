"""Models as op lists, cut into stages at the aggregation markers."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class NotIncremental(ValueError):
    """The model holds an op that grouped updates can't bring up to date."""


@dataclass(frozen=True)
class Dense:
    weights: np.ndarray  # (out, in)


@dataclass(frozen=True)
class Bias:
    value: float


@dataclass(frozen=True)
class Relu:
    pass


@dataclass(frozen=True)
class Select:
    """Aggregation marker."""

    how: str = "min"


@dataclass(frozen=True)
class Combine:
    """weights . aggregate + own . message"""

    weights: np.ndarray
    own: np.ndarray


@dataclass(frozen=True)
class AddSelf:
    """aggregate + (1 + eps) * message"""

    eps: float = 0.0


@dataclass(frozen=True)
class Attention:
    """Softmax over the neighbours of a leaky score; full inference only."""

    left: np.ndarray
    right: np.ndarray
    slope: float = 0.2


@dataclass(frozen=True)
class Unsupported:
    """An op that depends on more than a node's own aggregate, by name (batch or graph norm, degree weights)."""

    name: str


@dataclass(frozen=True)
class Joined:
    """Width of the vectors that the user's ``apply`` hands to the tail; it stands right after a marker."""

    width: int


@dataclass(frozen=True)
class Hooks:
    """User events beside the native ones.

    ``emit`` gets changed messages (node_id, old, new; all of them, with null ``old``, in a full pass) and the stage's number
    and gives rows (node_id, vec); ``merge`` makes one row of those of a node (the last by default); the newest row of
    each node is kept with the state. ``apply`` gets rows (node_id, agg, ..) and the user rows of these nodes and
    gives the rows that the tail reads. Full passes run the same hooks, so both modes agree.
    """

    emit: Callable[[DataFrame, int], DataFrame] | None = None
    merge: Callable[[DataFrame], DataFrame] | None = None
    apply: Callable[[DataFrame, DataFrame], DataFrame] | None = None

    def merged(self, changed: DataFrame, stage: int) -> DataFrame:
        rows = self.emit(changed, stage)
        return self.merge(rows) if self.merge is not None else rows


@dataclass(frozen=True)
class Stage:
    marker: object | None  # None for the ops before the first marker
    tail: tuple
    width: int  # of the vectors that enter
    joined: int = 0  # of the vectors that the user's hooks make of them

    @property
    def tail_width(self) -> int:
        return self.joined or self.width

    @property
    def self_term(self) -> bool:
        return any(isinstance(op, (Combine, AddSelf)) for op in self.tail)


@dataclass(frozen=True)
class ModelSpec:
    name: str
    ops: tuple
    width: int  # of the features
    hooks: Hooks = field(default_factory=Hooks)
    empty_fill: float = 0.0

    def with_hooks(self, emit=None, merge=None, apply=None) -> ModelSpec:
        return ModelSpec(self.name, self.ops, self.width, Hooks(emit, merge, apply), self.empty_fill)

    def stages(self) -> list[Stage]:
        """Stage 0: ops before the first marker; then one stage for each marker, not for each layer."""
        out, marker, tail, width, entered, joined = [], None, [], self.width, self.width, 0
        for op in self.ops:
            if isinstance(op, (Select, Attention)):
                out.append(Stage(marker, tuple(tail), entered, joined))
                marker, tail, entered, joined = op, [], width, 0
                continue
            if isinstance(op, Joined):
                width = joined = op.width
                continue
            tail.append(op)
            if isinstance(op, (Dense, Combine)):
                if op.weights.shape[1] != width:
                    raise ValueError(f"{self.name}: {type(op).__name__} reads {op.weights.shape[1]} positions of {width}")
                width = op.weights.shape[0]
        return [*out, Stage(marker, tuple(tail), entered, joined)]

    @property
    def k(self) -> int:
        return len(self.stages()) - 1


def validate(model: ModelSpec) -> None:
    """Raises :class:`NotIncremental` with the op's name unless every op suits grouped updates."""
    for op in model.ops:
        if isinstance(op, Attention):
            raise NotIncremental("attention")
        if isinstance(op, Unsupported):
            raise NotIncremental(op.name)
        if isinstance(op, Select) and op.how not in ("min", "max"):
            raise NotIncremental(f"select {op.how}")


def run_ops(ops: tuple, agg: np.ndarray | None, own: np.ndarray) -> np.ndarray:
    """The tail of a stage on rows of vectors; zeros are positive, and sums run in a fixed order."""
    x = own if agg is None else agg
    for op in ops:
        if isinstance(op, Dense):
            x = _product(x, op.weights)
        elif isinstance(op, Bias):
            x = x + op.value
        elif isinstance(op, Relu):
            x = np.maximum(x, 0.0)
        elif isinstance(op, Combine):
            x = _product(x, op.weights) + _product(own, op.own)
        elif isinstance(op, AddSelf):
            x = x + (1 + op.eps) * own
        else:
            raise NotIncremental(type(op).__name__)
    return x + 0.0


def _product(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Products row by row, whatever the number of rows, so a row's result has the same bits in any batch."""
    return np.einsum("ni,oi->no", x, w, optimize=False)


def fixed_weights(out: int, n: int, shift: int = 0) -> np.ndarray:
    """Two +1 and one -1 in each row, by rule: all sums of integers stay exact."""
    w = np.zeros((out, n))
    for j in range(out):
        for factor, add, value in ((3, 1, 1.0), (5, 2, 1.0), (7, 4, -1.0)):
            w[j, (factor * j + add + shift) % n] += value
    return w


#: Added after each transform, so that outputs stay alive under min and ReLU.
BIAS = 65536.0


def gcn(k: int = 2, d: int = 256, select: str = "min", width: int | None = None, order: str = "transform_first") -> ModelSpec:
    n, ops = width or d, []
    for _ in range(k):
        dense = Dense(fixed_weights(d, n))
        ops += [dense, Select(select), Bias(BIAS), Relu()] if order == "transform_first" else [Select(select), dense, Bias(BIAS), Relu()]
        n = d
    return ModelSpec("gcn" if order == "transform_first" else "gcn_aggfirst", tuple(ops), width or d)


def sage(k: int = 2, d: int = 256, select: str = "min", width: int | None = None) -> ModelSpec:
    n, ops = width or d, []
    for _ in range(k):
        ops += [Select(select), Combine(fixed_weights(d, n), fixed_weights(d, n, 1)), Bias(BIAS), Relu()]
        n = d
    return ModelSpec("sage", tuple(ops), width or d)


def isonet(k: int = 5, d: int = 64, select: str = "max", width: int | None = None, eps: float = 0.0) -> ModelSpec:
    n, ops = width or d, []
    for _ in range(k):
        ops += [Select(select), AddSelf(eps), Dense(fixed_weights(d, n)), Bias(BIAS), Relu(), Dense(fixed_weights(d, d)), Bias(BIAS), Relu()]
        n = d
    return ModelSpec("isonet", tuple(ops), width or d)


def sage_by_hooks(k: int = 2, d: int = 256, select: str = "min") -> ModelSpec:
    """GraphSAGE whose self-term is the user's: a changed message is an event for its own node."""
    emit = lambda changed, stage: changed.select("node_id", F.col("new").alias("vec"))
    beside = lambda: F.concat(F.coalesce("agg", F.array_repeat(F.lit(0.0), d)), "vec").alias("agg")
    apply = lambda rows, own: rows.join(own, "node_id").select("node_id", beside())
    dense = np.hstack([fixed_weights(d, d), fixed_weights(d, d, 1)])
    return ModelSpec("sage_by_hooks", (Select(select), Joined(2 * d), Dense(dense), Bias(BIAS), Relu()) * k, d).with_hooks(emit, apply=apply)


ZOO = {"gcn": gcn, "sage": sage, "isonet": isonet}

"""Models: layers with frozen weights, and the exact formula weights of the fixtures."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

AGGREGATORS = ("sum", "mean", "wsum", "norm", "sum_mean", "max", "min", "attention")
INVERTIBLE = ("sum", "mean", "wsum", "norm", "sum_mean")


class NonInvertibleAggregator(ValueError):
    """The aggregate has no inverse, so deltas cannot maintain it; use the recompute strategies."""


@dataclass(frozen=True)
class LinearAggregator:
    """A linear aggregate of one's own as SQL texts: ``weight`` of {w} scales what an edge carries, sums of these
    are stored, added to and subtracted from, and ``finish`` of the sum {s} and the in-degree {c} enters the matrix."""

    weight: str = "1D"
    finish: str = "{s}"


#: aggregators that users add: name -> LinearAggregator
CUSTOM: dict[str, LinearAggregator] = {}


def register_aggregator(name: str, aggregator: LinearAggregator) -> None:
    """Make ``LayerSpec(agg=name)`` usable in every strategy."""
    if name in AGGREGATORS:
        raise ValueError(f"{name} is built in")
    CUSTOM[name] = aggregator


#: weights squared, smoothed by the in-degree: an aggregate beside the built-in ones
register_aggregator("smoothed", LinearAggregator("{w} * {w}", "{s} / ({c} + 1)"))


@dataclass(frozen=True)
class LayerSpec:
    """One layer: aggregate in-neighbours, combine with the own vector, activate.

    conv: ``gc`` (aggregate only), ``sage`` (own vector times w_self added), ``gin`` (own vector times
    1 + eps added before a two-matrix perceptron)."""

    conv: str
    agg: str
    d_in: int
    d_out: int
    w: tuple[tuple[float, ...], ...]
    w_self: tuple[tuple[float, ...], ...] | None = None
    bias: tuple[float, ...] | None = None
    eps: float = 0.0
    act: str = "relu"

    @property
    def self_dependent(self) -> bool:
        return self.conv in ("sage", "gin")

    @property
    def weighted(self) -> bool:
        return self.agg == "wsum"

    @property
    def agg_width(self) -> int:
        """Width of what goes into the matrix: two aggregates side by side double it."""
        return 2 * self.d_in if self.agg == "sum_mean" else self.d_in

    @property
    def custom(self) -> LinearAggregator | None:
        return CUSTOM.get(self.agg)

    def require_inverse(self) -> None:
        if self.agg not in INVERTIBLE and not self.custom:
            raise NonInvertibleAggregator(self.agg)


@dataclass(frozen=True)
class ModelSpec:
    name: str
    layers: tuple[LayerSpec, ...] = field(default_factory=tuple)

    @property
    def depth(self) -> int:
        return len(self.layers)

    @property
    def exact(self) -> bool:
        """Whether sums of dyadic inputs stay exact (no division)."""
        return all(x.agg in ("sum", "wsum") for x in self.layers)


def formula_weight(i: int, j: int, layer: int) -> float:
    return ((7 * i + 3 * j + 5 * layer) % 11 - 5) / 8


def formula_self(i: int, j: int, layer: int) -> float:
    return ((5 * i + 11 * j + 3 * layer) % 13 - 6) / 8


def formula_bias(j: int, layer: int) -> float:
    return ((3 * j + layer) % 5 - 2) / 8


def second_weight(i: int, j: int, last: bool) -> float:
    """The second set, under which labels of dense graphs do not collapse."""
    return (1 - 2 * ((i & (j + (1 if last else 0))).bit_count() % 2)) / 8


#: workload name -> (conv, aggregator)
KINDS = {
    "gc_sum": ("gc", "sum"), "sage_sum": ("sage", "sum"), "gc_mean": ("gc", "mean"), "gin_sum": ("gin", "sum"), "gc_wsum": ("gc", "wsum"),
    "sage_mean": ("sage", "mean"), "gc_norm": ("gc", "norm"), "gc_sum_mean": ("gc", "sum_mean"), "gc_max": ("gc", "max"), "gc_min": ("gc", "min"), "gc_attention": ("gc", "attention"), "gc_smoothed": ("gc", "smoothed"),
}
WORKLOADS = ("gc_sum", "sage_sum", "gc_mean", "gin_sum", "gc_wsum")


def make_model(kind: str, depth: int, d: int = 8, classes: int | None = None, weights: str = "first", bias: bool = False) -> ModelSpec:
    conv, agg = KINDS[kind]
    layers = []
    for layer in range(depth):
        last = layer == depth - 1
        d_out = (classes or d) if last else d
        spec = LayerSpec(conv, agg, d, d_out, (), act="identity" if last else "relu", eps=0.5 if conv == "gin" else 0.0)
        own = (lambda i, j: formula_weight(i, j, layer)) if weights == "first" else (lambda i, j: second_weight(i, j, last))
        mid = d if conv == "gin" else d_out
        w = tuple(tuple(own(i, j) for j in range(mid)) for i in range(spec.agg_width))
        w_self = tuple(tuple(formula_self(i, j, layer) for j in range(d_out)) for i in range(d)) if conv != "gc" else None
        layers.append(replace(spec, w=w, w_self=w_self, bias=tuple(formula_bias(j, layer) for j in range(d_out)) if bias else None))
    return ModelSpec(f"{kind}_{depth}l", tuple(layers))


def model_rows(model: ModelSpec) -> list[tuple[int, str, int, int, float]]:
    """(layer, role, i, j, w): the trained weights as a table."""
    return [
        (layer, role, i, j, w)
        for layer, spec in enumerate(model.layers)
        for role, matrix in (("w", spec.w), ("w_self", spec.w_self or ()))
        for i, row in enumerate(matrix)
        for j, w in enumerate(row)
    ]

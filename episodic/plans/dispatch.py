"""Which way to count: over candidates or over segments. The rule compares candidates with capacity times f(size)."""

from __future__ import annotations

from dataclasses import dataclass, field

# Measured crossover points of the published experiment by episode size, and its capacity product.
PRINTED_CROSSOVERS = {3: 415, 4: 190, 5: 200, 6: 100, 7: 100, 8: 60}
PRINTED_CAPACITY = 30 * 32 * 1
LEAST_F = 0.01


@dataclass(frozen=True)
class CrossoverModel:
    """f(N) = a / N + b ("reciprocal") or a * N + b ("linear"), never below LEAST_F; sizes in `override` are decided by it."""

    a: float
    b: float
    form: str = "reciprocal"
    r2: float = 0.0
    sse: float = 0.0
    override: dict = field(default_factory=dict)
    largest: int = 8

    def f(self, n: int) -> float:
        return max(LEAST_F, (self.a / n if self.form == "reciprocal" else self.a * n) + self.b)


def fit_crossover(points: dict[int, float], capacity: float = PRINTED_CAPACITY, form: str = "reciprocal") -> CrossoverModel:
    """Least squares of crossover / capacity on 1 / N or N."""
    if form not in ("reciprocal", "linear"):
        raise ValueError("form is reciprocal or linear")
    xs = [1 / n if form == "reciprocal" else float(n) for n in points]
    ys = [c / capacity for c in points.values()]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    sxx = sum((x - mx) ** 2 for x in xs)
    a = sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sxx
    b = my - a * mx
    sse = sum((y - a * x - b) ** 2 for x, y in zip(xs, ys, strict=True))
    syy = sum((y - my) ** 2 for y in ys)
    return CrossoverModel(a, b, form, 1 - sse / syy if syy else 1.0, sse)


def printed_model() -> CrossoverModel:
    """The reciprocal fit of the printed points with the note's preference for segments at sizes 1, 2 and above 8."""
    m = fit_crossover(PRINTED_CROSSOVERS)
    return CrossoverModel(m.a, m.b, m.form, m.r2, m.sse, {1: "segment", 2: "segment"}, 8)


def choose_counting(candidates: int, nodes: int, slots: int, batch: int = 32, model: CrossoverModel | None = None) -> str:
    """ "episode" if the candidates exceed slots * batch * f(nodes), else "segment"."""
    model = model or printed_model()
    if nodes in model.override:
        return model.override[nodes]
    if nodes > model.largest:
        return "segment"
    return "episode" if candidates > slots * batch * model.f(nodes) else "segment"

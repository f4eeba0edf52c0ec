"""Generators of Bregman divergences.

A generator is a convex function of one coordinate; the divergence of vectors is the sum over coordinates
of ``phi(x) - phi(y) - grad(y) (x - y)``. Each is given once as SQL text (for Spark and for other
engines) and once for NumPy.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Array = np.ndarray


@dataclass(frozen=True)
class Generator:
    """``phi_sql``/``grad_sql`` hold ``{t}``; ``term_sql``, of ``{a}`` and ``{b}``, where a closed form is more exact."""

    name: str
    phi_sql: str
    grad_sql: str
    phi: Callable[[Array], Array]
    grad: Callable[[Array], Array]
    grad_inv: Callable[[Array], Array]
    domain: str = "real"  # or "positive"
    term_sql: str | None = None
    weights: tuple[float, ...] = field(default=())

    def term(self, a: str, b: str) -> str:
        """SQL of one coordinate's divergence."""
        if self.term_sql:
            return self.term_sql.format(a=a, b=b)
        return f"({self.phi_sql.format(t=a)} - ({self.phi_sql.format(t=b)}) - ({self.grad_sql.format(t=b)}) * ({a} - {b}))"

    def prepared(self, df: DataFrame, vec: str = "vec") -> DataFrame:
        """Weighted generators work on coordinates scaled by the roots of the weights."""
        if not self.weights:
            return df
        roots = "array(" + ",".join(f"{w ** 0.5!r}D" for w in self.weights) + ")"
        return df.withColumn(vec, F.expr(f"zip_with({vec}, {roots}, (v, w) -> v * w)"))

    def divergence(self, x: Array, y: Array) -> Array:
        """Row by row in difference form; x and y broadcast."""
        if self.name in ("itakura_saito", "burg"):
            r = x / y
            return np.maximum((r - np.log(r) - 1).sum(-1), 0)
        if self.name == "squared_euclidean":
            return 0.5 * ((x - y) ** 2).sum(-1)
        if self.name == "exponential":
            return np.maximum((np.exp(y) * (np.expm1(x - y) - (x - y))).sum(-1), 0)
        return np.maximum((self.phi(x) - self.phi(y) - self.grad(y) * (x - y)).sum(-1), 0)

    def matrix(self, x: Array, y: Array) -> Array:
        """All of x (n, d) against all of y (q, d) by one matrix product: (n, q), clipped at 0."""
        g = self.grad(y)
        return np.maximum(self.phi(x).sum(1)[:, None] - x @ g.T + ((g * y).sum(1) - self.phi(y).sum(1))[None, :], 0)

    def pairs(self, x: Array, y: Array) -> Array:
        """As ``matrix``, but small divergences, where the product cancels, are measured in difference form."""
        out = self.matrix(x, y)
        size = np.abs(self.phi(x)).sum(1)[:, None] + np.abs(self.grad(y) * y).sum(1)[None, :]
        row, col = np.nonzero(out <= 1e-6 * size)
        for lo in range(0, len(row), 1 << 14):
            i, j = row[lo : lo + (1 << 14)], col[lo : lo + (1 << 14)]
            out[i, j] = self.divergence(x[i], y[j])
        return out


def squared_euclidean() -> Generator:
    return Generator("squared_euclidean", "({t}*{t}/2)", "{t}", lambda t: t * t / 2, lambda t: t, lambda s: s, term_sql="(({a}-{b})*({a}-{b})/2)")


def mahalanobis(weights: list[float]) -> Generator:
    """Diagonal case; vectors are scaled by ``prepared`` first. For a full matrix see ``whiten``."""
    if min(weights) <= 0:
        raise ValueError("weights must be positive")
    return Generator("squared_euclidean", "({t}*{t}/2)", "{t}", lambda t: t * t / 2, lambda t: t, lambda s: s, term_sql="(({a}-{b})*({a}-{b})/2)", weights=tuple(map(float, weights)))


def itakura_saito() -> Generator:
    return Generator("itakura_saito", "(-ln({t}))", "(-1/{t})", lambda t: -np.log(t), lambda t: -1 / t, lambda s: -1 / s, "positive", "({a}/{b} - ln({a}/{b}) - 1)")


def burg() -> Generator:
    return Generator("burg", "(-ln({t}))", "(-1/{t})", lambda t: -np.log(t), lambda t: -1 / t, lambda s: -1 / s, "positive", "({a}/{b} - ln({a}/{b}) - 1)")


def exponential() -> Generator:
    return Generator("exponential", "exp({t})", "exp({t})", np.exp, np.exp, np.log)


def shannon() -> Generator:
    return Generator("shannon", "({t}*ln({t})-{t})", "ln({t})", lambda t: t * np.log(t) - t, np.log, np.exp, "positive")


def lp_norm(p: float = 3.0) -> Generator:
    if p <= 1:
        raise ValueError("p must exceed 1; for 0 < p < 1 see lp_quasi")
    return Generator(
        f"lp_{p:g}", f"pow(abs({{t}}),{p!r})", f"({p!r}*sign({{t}})*pow(abs({{t}}),{p - 1!r}))",
        lambda t: np.abs(t) ** p, lambda t: p * np.sign(t) * np.abs(t) ** (p - 1), lambda s: np.sign(s) * (np.abs(s) / p) ** (1 / (p - 1)),
    )


def lp_quasi(p: float = 0.5) -> Generator:
    if not 0 < p < 1:
        raise ValueError("p must be between 0 and 1")
    return Generator(
        f"lp_quasi_{p:g}", f"(-pow({{t}},{p!r}))", f"(-{p!r}*pow({{t}},{p - 1!r}))",
        lambda t: -(t**p), lambda t: -p * t ** (p - 1), lambda s: (-s / p) ** (1 / (p - 1)), "positive",
    )


def kl() -> Generator:
    raise ValueError("the normalised relative entropy is not a sum over blocks of coordinates; use shannon(), its unnormalised form")


_REGISTRY = {
    "squared_euclidean": squared_euclidean, "mahalanobis": mahalanobis, "itakura_saito": itakura_saito, "isd": itakura_saito, "burg": burg,
    "exponential": exponential, "exp": exponential, "shannon": shannon, "lp_norm": lp_norm, "lp_quasi": lp_quasi, "kl": kl,
}


def get(name: str, **kw) -> Generator:
    if name not in _REGISTRY:
        raise ValueError(f"unknown generator {name}; known: {', '.join(sorted(_REGISTRY))}")
    return _REGISTRY[name](**kw)


def custom(name: str, phi_sql: str, grad_sql: str, phi, grad, grad_inv, domain: str = "real") -> Generator:
    return Generator(name, phi_sql, grad_sql, phi, grad, grad_inv, domain)


def divergence(gen: Generator, x: str, y: str) -> Column:
    """Column of the divergence of two array columns, clipped at 0."""
    return F.expr(f"greatest(aggregate(zip_with({x}, {y}, (a, b) -> {gen.term('a', 'b')}), 0D, (s, v) -> s + v), 0D)")


def check_domain(df: DataFrame, gen: Generator, d: int, vec: str = "vec") -> DataFrame:
    """``df`` that fails while it is read if a vector is null, of another length, not finite, or outside the domain."""
    low = "v > 0" if gen.domain == "positive" else "true"
    good = F.expr(f"{vec} is not null and size({vec}) = {d} and forall({vec}, v -> v is not null and not isnan(v) and abs(v) < double('infinity') and {low})")
    checked = F.when(F.assert_true(F.coalesce(good, F.lit(False)), f"vector outside the domain of {gen.name}, or not of {d} numbers").isNull(), F.col(vec))
    return df.withColumn(vec, checked)


def shift_positive(df: DataFrame, eps: float, vec: str = "vec") -> DataFrame:
    """Coordinates moved up so that the smallest one is ``eps``."""
    low = df.agg(F.min(F.array_min(vec)).alias("low")).first()["low"]
    return df if low is None else df.withColumn(vec, F.expr(f"transform({vec}, v -> v - ({float(low)!r}D) + {float(eps)!r}D)"))


def whiten(df: DataFrame, q: Array, vec: str = "vec") -> DataFrame:
    """Coordinates in which a full quadratic form becomes the plain one: the squared Euclidean generator then serves."""
    factor = np.linalg.cholesky(np.asarray(q, float))

    def turn(batches):
        import pyarrow as pa

        for b in batches:
            i = b.schema.get_field_index(vec)
            x = b.column(i).flatten().to_numpy().reshape(b.num_rows, -1) @ factor
            flat = pa.array(x.ravel())
            yield b.set_column(i, vec, pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1] or 1), pa.int32()), flat))

    return df.mapInArrow(turn, df.schema)

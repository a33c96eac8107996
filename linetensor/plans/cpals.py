"""CP decomposition by alternating least squares over any kernel."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.factors import gram, normalise, rank_of, seeded_factor, times_matrix
from ..operators.kernels import densify, kr
from ..operators.packed import PackedTensor
from ..sources.tensors import checkpointed

Kernel = Callable[[Sequence[DataFrame], int], DataFrame]


@dataclass
class CpModel:
    """weights of the components, one factor for each mode, and the fit after every sweep."""

    weights: np.ndarray
    factors: list[DataFrame]
    fits: list[float] = field(default_factory=list)

    @property
    def iterations(self) -> int:
        return len(self.fits)


def packed_kernel(t: PackedTensor, resolve: str = "auto") -> Kernel:
    return lambda factors, mode: kr(t, factors, mode, resolve)


def system(grams: Sequence[np.ndarray], mode: int) -> np.ndarray:
    """Pseudo-inverse of the product, entry by entry, of the other modes' Gram matrices."""
    product = np.ones_like(grams[0])
    for m, g in enumerate(grams):
        if m != mode:
            product = product * g
    return np.linalg.pinv(product)


def als_update(kernel: Kernel, factors: Sequence[DataFrame], grams: Sequence[np.ndarray], mode: int, length: int) -> tuple[DataFrame, DataFrame]:
    """The kernel's output of a mode, and the least-squares factor that it gives, before scaling."""
    out = checkpointed(densify(kernel(factors, mode), length))
    return out, times_matrix(out, system(grams, mode), "y")


def fit_of(norm_x: float, weights: np.ndarray, grams: Sequence[np.ndarray], out: DataFrame, last: DataFrame) -> float:
    """One minus the relative residual, from Gram matrices and the last kernel output: the model is never formed."""
    product = np.outer(weights, weights)
    for g in grams:
        product = product * g
    rank = rank_of(last)
    row = out.join(last, "idx").agg(*[F.sum(F.col(f"y{r}") * F.col(f"f{r}")).alias(f"i{r}") for r in range(rank)]).first()
    inner = float(np.array([v or 0.0 for v in row]) @ weights)
    residual = max(0.0, norm_x**2 + float(product.sum()) - 2 * inner)
    return 1.0 - np.sqrt(residual) / norm_x if norm_x else 1.0


def cp_als(values: DataFrame, kernel: Kernel, lengths: Sequence[int], rank: int, iterations: int = 10, tol: float = 1e-5, seed: int = 1, factors: Sequence[DataFrame] | None = None) -> CpModel:
    """Alternate over the modes until the fit changes by less than tol. values has the elements' ``val``.

    Factors are cut from their lineage after every update, so a sweep repeats nothing of the last.
    """
    spark = values.sparkSession
    held = list(factors or [seeded_factor(spark, n, rank, m, seed) for m, n in enumerate(lengths)])
    norm_x = float(values.agg(F.sqrt(F.coalesce(F.sum(F.col("val") * F.col("val")), F.lit(0.0)))).first()[0])
    grams = [gram(f) for f in held]
    weights, fits = np.ones(rank), []
    for sweep in range(iterations):
        for mode in range(len(lengths)):
            out, raw = als_update(kernel, held, grams, mode, lengths[mode])
            scaled, weights = normalise(raw, "l2" if sweep == 0 else "max")
            if sweep:  # later sweeps only shrink columns that grew beyond one
                weights = np.maximum(weights, 1.0)
                scaled = raw.select("idx", *[(F.col(f"f{r}") / float(w)).alias(f"f{r}") for r, w in enumerate(weights)])
            held[mode] = checkpointed(scaled)
            grams[mode] = gram(held[mode])
        fits.append(fit_of(norm_x, weights, grams, out, held[-1]))
        if len(fits) > 1 and abs(fits[-1] - fits[-2]) < tol:
            break
    return CpModel(weights, held, fits)

"""Leading eigenvalues, predicted costs, and the width they recommend."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from .chain import Chain
from .convergence import predicted_iterations
from .solve import subspace

SPARE = 6  # columns beyond the eigenvalues asked for, which hasten them


def leading(chain: Chain, width: int, want: int | None = None, tol: float = 1e-6, max_iter: int = 200) -> DataFrame:
    """rank, re, im, magnitude, residual of the leading ``want`` eigenvalues, by general subspace iteration on ``width`` columns (more of them
    converge faster). Raises where ``max_iter`` steps do not bring every residual below ``tol``."""
    solved, pairs = subspace(chain, width, want or width, tol, max_iter)
    if not solved.converged:
        raise RuntimeError(f"{chain.name}: {want or width} eigenvalues have not converged in {max_iter} steps")
    return pairs


def dense_spectrum(edges: DataFrame) -> np.ndarray:
    """All eigenvalues of a small chain by falling magnitude."""
    t = edges.select("src", "dst", "prob").toArrow()
    src, dst, prob = (t.column(c).to_numpy() for c in ("src", "dst", "prob"))
    names = np.unique(np.concatenate([src, dst]))
    p = np.zeros((len(names), len(names)))
    np.add.at(p, (np.searchsorted(names, src), np.searchsorted(names, dst)), prob)
    values = np.linalg.eigvals(p)
    return values[np.lexsort((np.abs(values - 1), -np.abs(values)))]


def costs(moduli: list[float], tol: float = 1e-10) -> list[dict]:
    """For each width s up to len(moduli) - 1: predicted steps and matvecs from abs(lambda_{s+1}); moduli by falling size, the first is 1."""
    out = []
    for s in range(1, len(moduli)):
        steps = predicted_iterations(moduli[s], tol)
        out.append({"width": s, "modulus": moduli[s], "steps": steps, "matvecs": s * steps})
    return out


def window_bounds(moduli: list[float], width: int, depth: int, tol: float = 1e-10) -> tuple[float, float]:
    """(least, most) predicted steps of a window: from abs(lambda_{ts+1}) and abs(lambda_{s+1})."""
    at = lambda i: moduli[i] if i < len(moduli) else 0.0
    return predicted_iterations(at(width * depth), tol), predicted_iterations(at(width), tol)


def crowding(moduli: list[float]) -> float:
    """The exponent a of 1 - abs(lambda_j) ~ j^a, by least squares over the moduli below 1: wide blocks pay for a > 1."""
    gaps = [(np.log(j), np.log(1 - m)) for j, m in enumerate(moduli[1:], start=1) if m < 1]
    if len(gaps) < 2:
        return 0.0
    x, y = np.array(gaps).T
    return float(np.polyfit(x, y, 1)[0])


def recommend(chain: Chain, max_width: int = 16, tol: float = 1e-10, passes: float | None = None, max_iter: int = 200) -> tuple[int, list[dict]]:
    """(width, table): the width with the fewest predicted matvecs, or (``passes`` given) the narrowest within so many passes."""
    moduli = [r.magnitude for r in leading(chain, max_width + 1 + SPARE, max_width + 1, tol=1e-4, max_iter=max_iter).orderBy("rank").collect()]
    table = costs(moduli, tol)
    if passes is not None:
        within = [r["width"] for r in table if r["steps"] <= passes]
        return (min(within) if within else table[-1]["width"]), table
    return min(table, key=lambda r: r["matvecs"])["width"], table

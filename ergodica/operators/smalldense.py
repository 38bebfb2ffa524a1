"""The small dense problems on the driver (or in a kernel): from a triangle of a tall QR to one vector of the basis.

The triangle is that of ``[W | Z]`` with ``Z = P^T W``; columns of ``W`` come scaled to unit length. Everything needed is in it:
``R11`` describes W, ``R12`` and ``R22`` the image. Coefficients returned are of W's columns.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

RANK_RTOL = 1e-13


@dataclass(frozen=True)
class Extraction:
    coefficients: np.ndarray  # of the basis columns
    residual: float  # of the unit vector, from the triangle
    rank: int
    ritz: complex  # the Ritz value chosen (1 for the least residual)
    values: np.ndarray  # all Ritz values or singular values


def image_of(extract: str, image: str | None) -> str:
    """``shifted`` (the window one step on, no pass of its own) or ``explicit`` (one pass more, on an orthonormal basis).

    By default what the extraction needs: the least residual lives with nearly parallel columns; Ritz values lose the digits that decide
    the rate to them, so they get the product of an orthonormal basis.
    """
    return image or ("explicit" if extract.startswith("ritz") else "shifted")


def triangle(w: np.ndarray, z: np.ndarray, scale: np.ndarray | float = 1.0, rows: int = 1 << 17) -> np.ndarray:
    """The triangle of ``[w | z] / scale``, some rows at a time: no copy of the basis is made."""
    r = np.zeros((0, w.shape[1] + z.shape[1]))
    for a in range(0, max(1, len(w)), rows):
        r = np.linalg.qr(np.vstack([r, np.hstack([w[a : a + rows] / scale, z[a : a + rows] / scale])]), mode="r")
    return r


def padded(r: np.ndarray) -> np.ndarray:
    """A triangle with fewer rows than columns (few states), filled with zeros."""
    return np.vstack([r, np.zeros((r.shape[1] - r.shape[0], r.shape[1]))]) if r.shape[0] < r.shape[1] else r


def truncate(r11: np.ndarray, rtol: float = RANK_RTOL) -> tuple[np.ndarray, int]:
    """(C, rank): W @ C is orthonormal and spans what of W is above ``rtol``."""
    _, s, vt = np.linalg.svd(r11)
    rank = max(1, int((s > rtol * s[0]).sum())) if s[0] > 0 else 1
    return vt[:rank].T / np.maximum(s[:rank], 1e-300), rank


def orthonormal(w: np.ndarray, rtol: float = RANK_RTOL) -> np.ndarray:
    """An orthonormal basis of what of W's span is above ``rtol``; the explicit image is taken of it, which keeps the digits that
    nearly parallel columns lose."""
    u, s, _ = np.linalg.svd(w / np.maximum(np.linalg.norm(w, axis=0), 1e-300), full_matrices=False)
    return u[:, : max(1, int((s > rtol * s[0]).sum()))]


def _parts(r: np.ndarray, scale: np.ndarray, rtol: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(C with scaling undone, coordinates of Q and of P^T Q in the triangle's basis, rank)."""
    r = padded(r)
    m = r.shape[1] // 2
    c, rank = truncate(r[:m, :m], rtol)
    q = np.vstack([r[:m, :m] @ c, np.zeros((r.shape[0] - m, rank))])
    return c / scale[:, None], q, r[:, m:] @ c, rank


def min_residual(r: np.ndarray, scale: np.ndarray, rtol: float = RANK_RTOL) -> Extraction:
    """The unit vector of the span with the least ||P^T v - v||: lowest eigenvector of the symmetric (P^T Q - Q)^T (P^T Q - Q)."""
    c, q, image, rank = _parts(r, scale, rtol)
    _, s, vt = np.linalg.svd(image - q, full_matrices=False)
    return Extraction(c @ vt[-1], float(s[-1]), rank, 1.0 + 0j, s)


def gram_residual(w: np.ndarray, z: np.ndarray, rtol: float = 1e-8) -> Extraction:
    """The same by normal equations (W^T W): cheap, but loses half the digits; kept as the documented fallback for loose tolerances."""
    scale = np.linalg.norm(w, axis=0)
    w, z = w / scale, z / scale
    values, u = np.linalg.eigh(w.T @ w)
    keep = values > rtol * values[-1]
    c = u[:, keep] / np.sqrt(values[keep])
    d = (z - w) @ c
    e, y = np.linalg.eigh(d.T @ d)
    return Extraction(c @ y[:, 0] / scale, float(np.sqrt(max(e[0], 0.0))), int(keep.sum()), 1.0 + 0j, e)


def _pick(values: np.ndarray, pick: str) -> int:
    if pick == "nearest_one":
        return int(np.argmin(np.abs(values - 1)))
    top = np.abs(values).max()
    near = np.flatnonzero(np.abs(values) >= top * (1 - 1e-12))
    return int(near[np.argmin(np.abs(values[near] - 1))])


def _real(y: np.ndarray) -> np.ndarray:
    """A complex vector turned so that its largest entry is real."""
    big = y[np.argmax(np.abs(y))]
    return np.real(y * np.conj(big) / abs(big))


def ritz_eig(r: np.ndarray, scale: np.ndarray, rtol: float = RANK_RTOL, pick: str = "magnitude") -> Extraction:
    """The Ritz vector of the dominant Ritz value, by eigendecomposition of Q^T P^T Q."""
    c, q, image, rank = _parts(r, scale, rtol)
    values, vectors = np.linalg.eig(q.T @ image)
    at = _pick(values, pick)
    y = _real(vectors[:, at])
    y = y / np.linalg.norm(y)
    return Extraction(c @ y, float(np.linalg.norm(image @ y - q @ y)), rank, complex(values[at]), values)


def ordered_schur(b: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """(U, T) with b = U T U^H and the diagonal of T by falling magnitude, or None if b is too far from diagonalisable."""
    values, vectors = np.linalg.eig(b)
    order = np.lexsort((np.abs(values - 1), -np.abs(values)))
    if np.linalg.cond(vectors) > 1e12:
        return None
    u, _ = np.linalg.qr(vectors[:, order])
    return u, u.conj().T @ b @ u


def ritz_schur(r: np.ndarray, scale: np.ndarray, rtol: float = RANK_RTOL) -> Extraction:
    """The first Schur vector of Q^T P^T Q with ordered diagonal; the eigenvector where no ordered form is reached."""
    c, q, image, rank = _parts(r, scale, rtol)
    found = ordered_schur(q.T @ image)
    if found is None:
        return ritz_eig(r, scale, rtol)
    u, t = found
    y = _real(u[:, 0])
    y = y / np.linalg.norm(y)
    return Extraction(c @ y, float(np.linalg.norm(image @ y - q @ y)), rank, complex(t[0, 0]), np.diag(t))


EXTRACTIONS = {"min_residual": min_residual, "ritz_eig": ritz_eig, "ritz_schur": ritz_schur}


def extract(w: np.ndarray, z: np.ndarray, how: str = "min_residual", rtol: float = RANK_RTOL) -> Extraction:
    """From a basis and its image held in one place."""
    scale = np.maximum(np.linalg.norm(w, axis=0), 1e-300)
    if how == "gram":
        return gram_residual(w, z)
    return EXTRACTIONS[how](triangle(w, z, scale), scale, rtol)

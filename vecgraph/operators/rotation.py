"""Rotations as exponentials of skew matrices, and how evenly they share variance among chunks."""

from __future__ import annotations

import numpy as np


def skew_of(theta: np.ndarray, d: int) -> np.ndarray:
    """The skew matrix whose strict upper triangle holds theta."""
    a = np.zeros((d, d))
    a[np.triu_indices(d, 1)] = theta
    return a - a.T


def spectrum(a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues (on the imaginary axis) and unitary eigenvectors of a skew matrix."""
    w, v = np.linalg.eigh(1j * a)
    return -1j * w, v


def rotation(a: np.ndarray) -> np.ndarray:
    lam, v = spectrum(a)
    return np.real((v * np.exp(lam)) @ v.conj().T)


def skew_log(r: np.ndarray) -> np.ndarray:
    """A skew matrix whose exponential is the rotation (of determinant one)."""
    w, v = np.linalg.eig(r)
    a = np.real(v @ np.diag(1j * np.angle(w)) @ np.linalg.inv(v))
    return (a - a.T) / 2


def positive(r: np.ndarray) -> np.ndarray:
    """The rotation with its first row turned around if its determinant is negative."""
    if np.linalg.det(r) < 0:
        r = r.copy()
        r[0] = -r[0]
    return r


def exp_adjoint(a: np.ndarray, g: np.ndarray) -> np.ndarray:
    """Gradient by the strict upper triangle of a, from the gradient g by exp(a): divided differences of exp on the spectrum."""
    lam, v = spectrum(a)
    e = np.exp(lam)
    gap = lam[:, None] - lam[None, :]
    same = np.abs(gap) < 1e-9
    phi = np.where(same, e[:, None], (e[:, None] - e[None, :]) / np.where(same, 1, gap))
    full = np.real(v @ ((v.conj().T @ g @ v) * phi.conj()) @ v.conj().T)
    return (full - full.T)[np.triu_indices(len(a), 1)]


def chunk_values(cov: np.ndarray, r: np.ndarray | None, m: int) -> np.ndarray:
    """Variance in each chunk after rotation."""
    c = cov if r is None else r @ cov @ r.T
    return np.diag(c).reshape(m, -1).sum(1)


def hadamard_rotation(d: int) -> np.ndarray:
    """Blocks of a 4x4 rotation whose entries are all 1/2 or -1/2: exact in binary arithmetic."""
    h = np.array([[1, 1, 1, 1], [1, -1, 1, -1], [1, 1, -1, -1], [1, -1, -1, 1]]) / 2
    return np.kron(np.eye(d // 4), h)

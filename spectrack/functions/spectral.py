"""Cosine transform (type II scaled by 2, inverse by 1/N) in several ways."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


@lru_cache(maxsize=256)
def basis(length: int, k: int) -> np.ndarray:
    """cos((2j+1) i pi / 2L): length x k."""
    j, i = np.arange(length)[:, None], np.arange(k)[None, :]
    return np.cos((2 * j + 1) * i * np.pi / (2 * length))


def choose(length: int, k: int) -> str:
    """A truncated product does k columns only and beats the fast transform on short blocks. Of a long block the basis would
    outgrow memory, however few columns are kept."""
    return "product" if length <= 256 or k * 8 <= length and length * k <= 1 << 18 else "fft"


def dct(v: np.ndarray, k: int | None = None, method: str | None = None, scaling: str = "two") -> np.ndarray:
    """Coefficients 0..k-1 of the rows of v."""
    v = np.atleast_2d(np.asarray(v, float))
    n = v.shape[1]
    k = n if k is None else min(k, n)
    method = method or choose(n, k)
    if method == "fft":  # the row and its mirror image, 2N points
        spectrum = np.fft.rfft(np.concatenate((v, v[:, ::-1]), axis=1), axis=1)[:, :k]
        c = (spectrum * np.exp(-1j * np.pi * np.arange(k) / (2 * n))).real
    elif method == "direct":
        c = np.stack([2 * (v * np.cos((2 * np.arange(n) + 1) * i * np.pi / (2 * n))).sum(axis=1) for i in range(k)], axis=1)
    else:
        c = 2 * (v @ basis(n, k))
    if scaling == "ortho":
        c = c * np.sqrt(1 / (2 * n))
        c[:, 0] *= np.sqrt(0.5)
    return c


def idct(c: np.ndarray, length: int, scaling: str = "two") -> np.ndarray:
    """Rows back from their first coefficients; the 0th counts half in the scaling by 2."""
    c = np.atleast_2d(np.asarray(c, float))
    k = c.shape[1]
    if scaling == "two" and choose(length, k) == "fft":  # the spectrum of the row and its mirror image
        i = np.arange(k)
        spectrum = np.zeros((len(c), length + 1), complex)
        spectrum[:, :k] = c * np.exp(1j * np.pi * i / (2 * length))
        return np.fft.irfft(spectrum, 2 * length, axis=1)[:, :length]
    if scaling == "ortho":
        return (c * np.where(np.arange(k) == 0, np.sqrt(1 / length), np.sqrt(2 / length))) @ basis(length, k).T
    return (c * np.where(np.arange(k) == 0, 0.5, 1.0)) @ basis(length, k).T / length

"""Unitary mixing of blocks of rows, in numpy. All give B real rows of equal total energy.

dft: half spectrum, real and imaginary parts stacked (scaled by sqrt 2 but for frequency 0
and B/2), so that the B real rows are an orthogonal transform. dct: type II. wht: Walsh-
Hadamard, B a power of two. none: rows as they are.
"""

from __future__ import annotations

import numpy as np

KINDS = ("dft", "dct", "wht", "none")


def mix(block: np.ndarray, kind: str = "dft") -> np.ndarray:
    """Transform along axis 0. For dft row 2f - 1 is the real and row 2f the imaginary part of frequency f."""
    b = block.shape[0]
    if kind == "none":
        return block
    if kind == "dft":
        f = np.fft.rfft(block, axis=0) / np.sqrt(b)
        out = np.empty(block.shape)
        out[0] = f[0].real
        top = (b - 1) // 2
        out[1 : 2 * top : 2] = np.sqrt(2) * f[1 : top + 1].real
        out[2 : 2 * top + 1 : 2] = np.sqrt(2) * f[1 : top + 1].imag
        if b % 2 == 0 and b > 1:
            out[b - 1] = f[b // 2].real
        return out
    if kind == "dct":
        f = np.fft.fft(np.concatenate([block, block[::-1]]), axis=0)[:b]
        turn = np.exp(-1j * np.pi * np.arange(b) / (2 * b)).reshape((b,) + (1,) * (block.ndim - 1))
        out = (f * turn).real / 2 * np.sqrt(2 / b)
        out[0] /= np.sqrt(2)
        return out
    if kind == "wht":
        if b & (b - 1):
            raise ValueError(f"a block of {b} rows: Walsh-Hadamard needs a power of two")
        out, h = block.astype(float).copy(), 1
        while h < b:
            out = out.reshape(b // (2 * h), 2, h, *block.shape[1:])
            out = np.stack([out[:, 0] + out[:, 1], out[:, 0] - out[:, 1]], axis=1).reshape(b, *block.shape[1:])
            h *= 2
        return out / np.sqrt(b)
    raise ValueError(f"unknown mixer {kind!r}")


def rows_of(kind: str, b: int, outputs: np.ndarray) -> np.ndarray:
    """The transform's rows for some outputs (len(outputs) by b): for blocks of which only few outputs are kept."""
    p, m = np.arange(b), np.asarray(outputs)
    if kind == "none":
        return (m[:, None] == p).astype(float)
    if kind == "dft":
        f = (m + 1) // 2
        angle = -2 * np.pi * np.outer(f, p) / b
        edge = (m == 0) | ((b % 2 == 0) & (m == b - 1))
        scale = np.where(edge, 1.0, np.sqrt(2.0))[:, None] / np.sqrt(b)
        return scale * np.where(((m % 2 == 1) | edge)[:, None], np.cos(angle), np.sin(angle))
    if kind == "dct":
        out = np.sqrt(2 / b) * np.cos(np.pi * np.outer(m, 2 * p + 1) / (2 * b))
        out[m == 0] /= np.sqrt(2)
        return out
    if kind == "wht":
        both = m[:, None] & p
        return (1 - 2.0 * (np.bitwise_count(both) & 1)) / np.sqrt(b)
    raise ValueError(f"unknown mixer {kind!r}")

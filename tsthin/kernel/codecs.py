"""Functional and lossless codecs: constant and linear pieces, Fourier truncation, XOR streams."""

from __future__ import annotations

import numpy as np


# -- piecewise models: lists of (start, length, intercept, slope) ------------------------------------------------------


def pmc_mean(x, tol: float) -> list[tuple[int, int, float, float]]:
    """Constant pieces: a piece ends before a value that would take its running mean farther than ``tol`` from its extremes."""
    out, start, n, total, lo, hi = [], 0, 0, 0.0, 0.0, 0.0
    for i, v in enumerate(map(float, x)):
        m, a, b = (total + v) / (n + 1), min(lo, v) if n else v, max(hi, v) if n else v
        if n and (b - m > tol or m - a > tol):
            out.append((start, n, total / n, 0.0))
            start, n, total, lo, hi = i, 1, v, v, v
        else:
            n, total, lo, hi = n + 1, total + v, a, b
    if n:
        out.append((start, n, total / n, 0.0))
    return out


def swing(x, tol: float) -> list[tuple[int, int, float, float]]:
    """Connected linear pieces from a pivot, within a cone of slopes; the end is the least-squares slope clipped to the cone."""
    x = np.asarray(x, float)
    out, n = [], len(x)
    if not n:
        return out
    pivot, value, i = 0, float(x[0]), 1
    lo, hi, su, sq = -np.inf, np.inf, 0.0, 0.0
    while i < n:
        t = i - pivot
        a, b = (x[i] - tol - value) / t, (x[i] + tol - value) / t
        if max(lo, a) > min(hi, b):
            slope = min(max(su / sq, lo), hi)
            out.append((pivot, i - 1 - pivot, value, slope))
            value, pivot = value + slope * (i - 1 - pivot), i - 1
            lo, hi, su, sq = -np.inf, np.inf, 0.0, 0.0
            continue
        lo, hi = max(lo, a), min(hi, b)
        su, sq = su + t * (x[i] - value), sq + t * t
        i += 1
    slope = min(max(su / sq, lo), hi) if sq else 0.0
    out.append((pivot, n - pivot, value, slope))
    return out


def cone_pieces(x, tol: float) -> list[tuple[int, int, float, float, float]]:
    """Pieces from intercepts rounded down to a multiple of ``tol``: (start, length, intercept, least slope, greatest slope)."""
    x = np.asarray(x, float)
    out, n, i = [], len(x), 0
    while i < n:
        b = float(np.floor(x[i] / tol) * tol) if tol > 0 else float(x[i])
        lo, hi, j = -np.inf, np.inf, i + 1
        while j < n:
            u, v = (x[j] - tol - b) / (j - i), (x[j] + tol - b) / (j - i)
            if max(lo, u) > min(hi, v):
                break
            lo, hi, j = max(lo, u), min(hi, v), j + 1
        out.append((i, j - i, b, lo if np.isfinite(lo) else 0.0, hi if np.isfinite(hi) else 0.0))
        i = j
    return out


def merge_cones(pieces) -> tuple[list[tuple[int, int, float, float]], int]:
    """Pieces of one intercept whose slope ranges meet share a slope; also the number of stored elements."""
    by: dict[float, list] = {}
    for p in pieces:
        by.setdefault(p[2], []).append(p)
    out, stored = [], 0
    for b, group in by.items():
        stored += 1
        run, lo, hi = [], 0.0, 0.0
        for p in sorted(group, key=lambda q: (q[3], q[0])):
            if run and p[3] <= hi:
                lo, hi = max(lo, p[3]), min(hi, p[4])
            else:
                out += [(q[0], q[1], b, (lo + hi) / 2) for q in run]
                stored += len(run) + bool(run)
                run, lo, hi = [], p[3], p[4]
            run.append(p)
        out += [(q[0], q[1], b, (lo + hi) / 2) for q in run]
        stored += len(run) + bool(run)
    return sorted(out), stored


def draw(pieces, n: int) -> np.ndarray:
    out = np.zeros(n)
    for start, length, b, slope in pieces:
        out[start : start + length] = b + slope * np.arange(min(length, n - start))
    return out


# -- Fourier ------------------------------------------------------------------------------------------------------------


def fourier(x, keep: int, pick: str = "low") -> tuple[np.ndarray, np.ndarray]:
    """Indices and values of the coefficients kept: the first, or those of greatest modulus and the mean."""
    f = np.fft.rfft(np.asarray(x, float))
    if pick == "low":
        at = np.arange(min(keep, len(f)))
    else:
        size = np.abs(f)
        size[0] = np.inf
        at = np.sort(np.argsort(-size, kind="stable")[:keep])
    return at, f[at]


def inverse_fourier(at, values, n: int) -> np.ndarray:
    f = np.zeros(n // 2 + 1, complex)
    f[np.asarray(at, int)] = values
    return np.fft.irfft(f, n) if n else np.zeros(0)


# -- XOR streams --------------------------------------------------------------------------------------------------------

#: Classes of leading zeros, fixed values.
LEADING = (0, 8, 12, 16, 18, 20, 22, 24)


def _zeros(x: int) -> tuple[int, int]:
    return 64 - x.bit_length(), (x & -x).bit_length() - 1


def _pack(bits: list[str]) -> tuple[bytes, int]:
    s = "".join(bits)
    return (int(s + "0" * (-len(s) % 8), 2).to_bytes((len(s) + 7) // 8, "big") if s else b""), len(s)


class _Reader:
    def __init__(self, payload: bytes, n_bits: int):
        self.s, self.at = (bin(int.from_bytes(b"\1" + payload, "big"))[3:])[:n_bits], 0

    def take(self, n: int) -> int:
        out = int(self.s[self.at : self.at + n], 2) if n else 0
        self.at += n
        return out


def xor_gorilla(x) -> tuple[bytes, int]:
    """Payload and its bits: first value raw; then 0, or 10 and the last window's bits, or 11, 5 + 6 bits of window and its bits."""
    words = np.asarray(x, float).view(np.uint64).tolist()
    bits, lead, width = [], -1, 0
    for i, w in enumerate(words):
        if not i:
            bits.append(f"{w:064b}")
            continue
        d = w ^ words[i - 1]
        if not d:
            bits.append("0")
            continue
        a, b = _zeros(d)
        a = min(a, 31)
        if lead >= 0 and a >= lead and b >= 64 - lead - width:
            bits.append("10" + f"{d >> (64 - lead - width):0{width}b}")
        else:
            lead, width = a, 64 - a - b
            bits.append(f"11{lead:05b}{width & 63:06b}{d >> b:0{width}b}")
    return _pack(bits)


def xor_gorilla_decode(payload: bytes, n_bits: int, n: int) -> np.ndarray:
    r, out, lead, width = _Reader(payload, n_bits), [], 0, 0
    for i in range(n):
        if not i:
            out.append(r.take(64))
        elif not r.take(1):
            out.append(out[-1])
        else:
            if r.take(1):
                lead, width = r.take(5), r.take(6) or 64
            out.append(out[-1] ^ (r.take(width) << (64 - lead - width)))
    return np.array(out, np.uint64).view(float)


def xor_chimp(x) -> tuple[bytes, int]:
    """As ``xor_gorilla`` with classed leading zeros: 00 equal; 01 many trailing zeros; 10 same class; 11 new class."""
    words = np.asarray(x, float).view(np.uint64).tolist()
    bits, last = [], -1
    for i, w in enumerate(words):
        if not i:
            bits.append(f"{w:064b}")
            continue
        d = w ^ words[i - 1]
        if not d:
            bits.append("00")
            last = -1
            continue
        a, b = _zeros(d)
        k = max(j for j, z in enumerate(LEADING) if z <= a)
        if b > 6:
            width = 64 - LEADING[k] - b
            bits.append(f"01{k:03b}{width & 63:06b}{d >> b:0{width}b}")
            last = -1
        elif k == last:
            bits.append(f"10{d:0{64 - LEADING[k]}b}")
        else:
            bits.append(f"11{k:03b}{d:0{64 - LEADING[k]}b}")
            last = k
    return _pack(bits)


def xor_chimp_decode(payload: bytes, n_bits: int, n: int) -> np.ndarray:
    r, out, last = _Reader(payload, n_bits), [], -1
    for i in range(n):
        if not i:
            out.append(r.take(64))
            continue
        flag = r.take(2)
        if flag == 0:
            out.append(out[-1])
            last = -1
        elif flag == 1:
            lead, width = LEADING[r.take(3)], r.take(6) or 64
            out.append(out[-1] ^ (r.take(width) << (64 - lead - width)))
            last = -1
        else:
            if flag == 3:
                last = r.take(3)
            out.append(out[-1] ^ r.take(64 - LEADING[last]))
    return np.array(out, np.uint64).view(float)

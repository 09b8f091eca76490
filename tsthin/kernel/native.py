"""The loops of ``Loops.java`` for long series. Every Spark machine has Java; where it lacks the compiler, NumPy's loops run on."""

from __future__ import annotations

import os
import shutil
import struct
import subprocess
from functools import cache
from pathlib import Path

import numpy as np

LONG = 5_000  #: points from which a series goes through the compiled loops, which take half a second to start
KINDS = {"mae": 0, "rmse": 1, "chebyshev": 2, "mape": 3}
SOURCE = Path(__file__).with_name("Loops.java")


def _run(points: int, sent: bytes) -> bytes:
    home = os.environ.get("JAVA_HOME")
    java = shutil.which("java", path=f"{home}/bin") if home else shutil.which("java")
    if java is None:
        raise FileNotFoundError("java")
    heap = 64 + points // 4000  # MB: at most some 200 bytes a point are held
    return subprocess.run([java, "-XX:+UseSerialGC", f"-Xmx{heap}m", str(SOURCE)], input=sent, check=True, capture_output=True).stdout


@cache
def _works() -> bool:
    """Whether Java compiles and runs the loops here; tried on three points."""
    try:
        sent = _state(0, np.zeros(3), (1,), 0, np.zeros(1), np.zeros((6, 1)), np.ones(3, bool)) + bytes(3) + _ends(0, 3, 0, 3, (0, 1, 0, 0, 0, 0), (0.0, np.inf, np.inf, 0.0))
        return len(_run(3, sent)) == 40 + 56 + 24
    except (OSError, subprocess.SubprocessError):
        return False


def usable(n: int, rules) -> bool:
    """Whether a series of so many points goes through the compiled loops under these rules."""
    plain = rules.window <= 1 and rules.statistic == "autocorr" and rules.distance in KINDS and not rules.hops_at_lags and len(rules.lags) > 0
    return LONG <= n < 2**27 and plain and min(rules.lags) > 0 and _works()


def _often(n: int, rules) -> int:
    """Removals from one rebuilding of the sums to the next: it reads the whole series, so longer ones have it at most 64 times."""
    return max(rules.recheck, n // 64) if rules.recheck else 0


def _state(what: int, x, lags, kind: int, base, sums, alive) -> bytes:
    heads = struct.pack("<4i", what, len(x), len(lags), kind) + np.array(lags, "<i4").tobytes()
    return heads + b"".join(np.asarray(a, "<f8").tobytes() for a in (base, sums, x)) + np.asarray(alive, np.uint8).tobytes()


def _ends(lo, hi, offset, total, whole, real) -> bytes:
    return struct.pack("<2i2q6i4d", lo, hi, offset, total, *whole, *real)


def thin_loop(series, eps: float, hops: int, mode: int = 0, most: float = np.inf) -> tuple[list[int], list[float], int]:
    """Runs ``series`` (of ``greedy.Series``) to its end: ``(removed, path, skipped)``. ``mode``: 0 by impact, 1 to 3 by area, steps and mean error."""
    rules, n = series.rules, len(series.x)
    skip, strict = mode == 0 and rules.on_violation == "skip", mode == 0 and rules.strict
    sent = _state(0, series.x, series.lags, KINDS[rules.distance], series.base, series.sums, series.alive) + np.asarray(series.fixed, np.uint8).tobytes()
    sent += _ends(series.lo, series.hi, series.offset, series.total, (mode, hops, _often(n, rules), rules.give_up, strict, skip), (eps, rules.ratio, most, series.deviation))
    got = _run(n, sent)
    done, skipped, live, evaluated, redrawn = struct.unpack_from("<5q", got)
    size = series.sums.size
    all_ = np.frombuffer(got, "<f8", 1 + size + done, 40)
    removed = np.frombuffer(got, "<i4", done, 40 + 8 * len(all_))
    series.x[:] = np.frombuffer(got, "<f8", n, 40 + 8 * len(all_) + 4 * done)
    series.deviation, series.sums, series.n_live, series.last = float(all_[0]), all_[1 : 1 + size].reshape(series.sums.shape).copy(), live, None
    series.alive[removed] = False
    kept = np.nonzero(series.alive)[0]
    series.left[kept[1:]], series.right[kept[:-1]] = kept[:-1], kept[1:]
    series.evaluated += evaluated
    series.redrawn += redrawn
    return removed.tolist(), all_[1 + size :].tolist(), skipped


def insert_loop(x: np.ndarray, drawn: np.ndarray, rules, keep: np.ndarray, sums, base, limit: int, to_bound: bool, euclidean: bool) -> np.ndarray:
    """``keep`` with the farthest points inserted, up to ``limit`` of all or to the bound by running sums."""
    sent = _state(1, drawn, rules.lags, KINDS[rules.distance], base, sums, keep) + np.asarray(x, "<f8").tobytes()
    return np.frombuffer(_run(2 * len(x), sent + struct.pack("<4id", limit, _often(len(x), rules), to_bound, euclidean, rules.eps)), np.uint8).astype(bool)

"""A causal self-attention language model in numpy, small enough to score a corpus.

One layer of one-head attention over windows of subword ids predicts the class of
the next id; within its class an id has its smoothed share of all training ids.
Classes come from a clustering of ids by their neighbours.  Windows overlap: each
scores its last ``STRIDE`` places and reads ``OVERLAP`` more before them, so every
id is scored once, in batches with one triangular mask.
"""

from __future__ import annotations

import ctypes
import math
from collections.abc import Callable
from functools import lru_cache
from importlib.util import find_spec
from pathlib import Path

import numpy as np

DIM, CLASSES, HASHED, STRIDE, OVERLAP, SEED = 16, 64, 1024, 24, 8, 5
WINDOW = STRIDE + OVERLAP
NAMES = ("by_class", "by_hash", "by_place", "q", "k", "v", "o", "u", "b")


@lru_cache(maxsize=1)
def one_thread() -> None:
    """Matrix products of this process in one thread: the products are small and
    Spark already runs a task on every core."""
    for lib in (Path(np.__file__).parent.parent / "numpy.libs").glob("*openblas*"):
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(f := ctypes.CDLL(str(lib)), name):
                getattr(f, name)(1)
                break


NEAR = 128


def neighbour_cells(ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Cells of the table of neighbours (``2 * NEAR`` for each id: those before, those after),
    one for each id and side, over texts laid end to end; pairs stay within a text."""
    inner = np.ones(len(ids), bool)
    inner[starts[:-1]] = False  # a text's first id has none before it
    after = np.flatnonzero(inner)
    a, b = ids[after - 1], ids[after]
    return np.concatenate([b * (2 * NEAR) + a % NEAR, a * (2 * NEAR) + NEAR + b % NEAR])


def project(seen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Totals and short vectors of rows of the table of neighbours."""
    total = seen.sum(1)
    of = np.random.default_rng(SEED).normal(size=(2 * NEAR, 24)).astype(np.float32)
    return total, np.sqrt(seen / np.maximum(total, 1)[:, None]).astype(np.float32) @ of


def cluster(total: np.ndarray, x: np.ndarray, end: int, classes: int = CLASSES, rounds: int = 8) -> np.ndarray:
    """Class of each id from the vectors of its neighbours; class 0 is the end id alone."""
    vocab = len(total)
    often = np.argsort(-total, kind="stable")
    out = (1 + np.arange(vocab) % (classes - 1)).astype(np.int64)
    known = np.flatnonzero(total > 0)
    if len(known) >= classes:
        centres = x[often[: classes - 1]].copy()
        for _ in range(rounds):
            near = np.argmin((centres * centres).sum(1) - 2 * x[known] @ centres.T, axis=1)
            for c in range(classes - 1):
                of = known[near == c]
                if len(of):
                    centres[c] = np.average(x[of], axis=0, weights=total[of])
        out[known] = near + 1
    out[end] = 0
    return out


def fresh() -> dict[str, np.ndarray]:
    rng = np.random.default_rng(SEED)
    f = lambda *s, at=0.1: (rng.normal(size=s) * at).astype(np.float32)
    d = DIM
    return {
        "by_class": f(CLASSES, d), "by_hash": f(HASHED, d), "by_place": f(WINDOW, d, at=0.02), "q": f(d, d, at=0.25), "k": f(d, d, at=0.25),
        "v": f(d, d, at=0.25), "o": f(d, d, at=0.25), "u": f(d, CLASSES), "b": np.zeros(CLASSES, np.float32),
    }


_LATE = np.triu(np.ones((WINDOW, WINDOW), bool), 1)


_SEEN = (~_LATE[OVERLAP:]).astype(np.float32)


def _sums(x: np.ndarray) -> np.ndarray:
    """Sums over the last axis, by a product: many short rows are slow to reduce."""
    return (x.reshape(-1, x.shape[-1]) @ np.ones(x.shape[-1], np.float32)).reshape(x.shape[:-1])


def _bounded(x: np.ndarray, most: int) -> np.ndarray:
    return np.minimum(x, most, out=x) if len(x) and x.max() > most else x


def _shares(q: np.ndarray, k: np.ndarray, real: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Weights of the places that each place sees, before they are divided by their sum;
    exponents are bounded, not shifted."""
    a = q @ np.ascontiguousarray(k.transpose(0, 2, 1))
    np.exp(_bounded(a, 60), out=a)
    a *= seen
    part = np.flatnonzero(~real.all(1))
    if len(part):
        a[part] *= real[part][:, None, :]
    return a


def _hidden(w: dict, late: np.ndarray, z: np.ndarray) -> np.ndarray:
    """Hidden vectors, with a one at their end for the bias."""
    out = np.empty((len(late), DIM + 1), np.float32)
    np.add(late, z @ w["o"], out=out[:, :DIM])
    out[:, DIM] = 1
    return out


def class_log_probs(w: dict, ids: np.ndarray, real: np.ndarray, goal: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Natural log probability of the goals' classes, for the last STRIDE places.

    The same numbers as training sees, with one division after the sum.
    """
    fx = np.take(w["by_class"], np.take(of, ids.ravel()), 0)
    fx += np.take(w["by_hash"], ids.ravel() % HASHED, 0)
    x = fx.reshape(*ids.shape, DIM)
    x += w["by_place"]
    kv = (fx @ np.concatenate([w["k"], w["v"]], 1)).reshape(*ids.shape, 2 * DIM)
    late = np.ascontiguousarray(x[:, OVERLAP:])
    q = (late.reshape(-1, DIM) @ (w["q"] * np.float32(1 / math.sqrt(DIM)))).reshape(late.shape)
    s = _shares(q, kv[:, :, :DIM], real, _SEEN)
    z = s @ kv[:, :, DIM:]
    z /= np.maximum(_sums(s), np.float32(1e-30))[:, :, None]
    y = _hidden(w, late.reshape(-1, DIM), z.reshape(-1, DIM)) @ np.concatenate([w["u"], w["b"][None]])
    _bounded(y, 80)
    own = np.take(y.ravel(), np.arange(0, y.size, CLASSES) + np.take(of, goal.ravel()))
    np.exp(y, out=y)
    return (own - np.log(_sums(y))).reshape(goal.shape)


def _rows_added(rows: np.ndarray, x: np.ndarray, size: int) -> np.ndarray:
    """Sums of the rows of ``x`` that go to each of ``size`` rows."""
    columns = x.T.astype(np.float64, order="C")
    return np.stack([np.bincount(rows, c, size) for c in columns], 1).astype(np.float32)


#: Windows worked on at once: what they need stays near the processor.
PART = 128


def _gradients(w: dict, ids: np.ndarray, real: np.ndarray, goal: np.ndarray, use: np.ndarray, of: np.ndarray, n: int) -> tuple[float, dict]:
    """Loss and gradients of some windows of a batch with ``n`` goals."""
    first, root = WINDOW - goal.shape[1], np.float32(1 / math.sqrt(DIM))
    hashed = ids.ravel() % HASHED
    own = np.take(of, ids.ravel())
    fx = np.take(w["by_class"], own, 0)
    fx += np.take(w["by_hash"], hashed, 0)
    x = fx.reshape(*ids.shape, DIM)
    x += w["by_place"]
    both = np.concatenate([w["k"], w["v"]], 1)
    kv = (fx @ both).reshape(*ids.shape, 2 * DIM)
    k, v = kv[:, :, :DIM], kv[:, :, DIM:]
    late = np.ascontiguousarray(x[:, first:])
    fl = late.reshape(-1, DIM)
    q = (fl @ (w["q"] * root)).reshape(late.shape)
    a = _shares(q, k, real, (~_LATE[first:]).astype(np.float32))
    part = 1 / np.maximum(_sums(a), np.float32(1e-30)).reshape(-1, 1)  # a itself is left undivided
    z = a @ v
    fz = z.reshape(-1, DIM)
    fz *= part
    flat = _hidden(w, fl, fz)
    e = flat @ np.concatenate([w["u"], w["b"][None]])
    _bounded(e, 80)
    weight = use.ravel().astype(np.float32)
    at = np.arange(0, e.size, CLASSES) + np.take(of, goal.ravel())
    hit = np.take(e.ravel(), at)
    np.exp(e, out=e)
    total = _sums(e)
    loss = float(((np.log(total) - hit) * weight).sum(dtype=np.float64) / n)
    # the gradient of the logits is e, less the total at the goal, times r
    e.ravel()[at] -= total
    r = (weight / n / total)[:, None]
    fh = e @ w["u"].T
    fh *= r
    flat *= r
    ub = flat.T @ e
    g = {"u": ub[:DIM], "b": ub[DIM], "o": fz.T @ fh}
    fdz = fh @ w["o"].T
    fdz *= part
    dz = fdz.reshape(z.shape)
    ds = dz @ np.ascontiguousarray(v.transpose(0, 2, 1))
    ds -= _sums(fdz * fz).reshape(*z.shape[:2], 1)
    ds *= a
    dkv = np.empty(kv.shape, np.float32)
    dkv[:, :, :DIM] = ds.transpose(0, 2, 1) @ q
    dkv[:, :, DIM:] = a.transpose(0, 2, 1) @ dz
    dkv = dkv.reshape(-1, 2 * DIM)
    dq = (ds @ k).reshape(-1, DIM)
    dq *= root
    g["q"] = fl.T @ dq
    g["k"], g["v"] = np.split(fx.T @ dkv, 2, 1)
    fdx = dkv @ both.T
    dx = fdx.reshape(x.shape)
    fh += dq @ w["q"].T
    dx[:, first:] += fh.reshape(late.shape)
    g["by_place"] = (np.ones(len(dx), np.float32) @ dx.reshape(len(dx), -1)).reshape(WINDOW, DIM)
    g["by_class"], g["by_hash"] = _rows_added(own, fdx, CLASSES), _rows_added(hashed, fdx, HASHED)
    return loss, g


@lru_cache(maxsize=1)
def loops() -> tuple[Callable, Callable, int]:
    """Gradients, class probabilities and windows worked on at once: by graphs of onnxruntime
    where it is installed, else by the numpy forms above."""
    if find_spec("onnxruntime"):
        from . import graphs

        return graphs.gradients, graphs.class_log_probs, graphs.PART
    return _gradients, class_log_probs, PART


def step(w: dict, m: dict, t: int, ids: np.ndarray, real: np.ndarray, goal: np.ndarray, use: np.ndarray, of: np.ndarray, rate: float) -> float:
    """One Adam step on a batch of windows, for the goals of their last places (as many as
    ``goal`` has); returns the mean loss."""
    loss, g, n = 0.0, {}, max(1, int(use.sum()))
    gradients, _, many = loops() if goal.shape[1] == STRIDE else (_gradients, None, PART)
    for lo in range(0, len(ids), many):
        s = slice(lo, lo + many)
        own, part = gradients(w, ids[s], real[s], goal[s], use[s], of, n)
        loss += own
        g = {name: d + g[name] for name, d in part.items()} if g else part
    fast, slow = np.float32(rate / (1 - 0.9**t)), np.float32(1 / (1 - 0.99**t))
    for name, d in g.items():
        one, two = m.setdefault(name, (np.zeros_like(d), np.zeros_like(d)))
        one += np.float32(0.1) * (d - one)
        two += np.float32(0.01) * (d * d - two)
        w[name] = w[name] - fast * one / (np.sqrt(slow * two) + np.float32(1e-8))
    return loss


def windows(ids: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, ...]:
    """Windows over texts laid end to end in ``ids``; each text begins and ends with the end id.

    ``starts`` are the offsets of the texts, with the total length last.  Returns
    inputs, which of them are real, goals, which goals are scored, and the text of
    each window; every id but a text's first is the goal of one scored place.
    """
    n = np.diff(starts) - 1  # goals of each text
    count = -(-n // STRIDE)
    text = np.repeat(np.arange(len(n)), count)
    nth = np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    at = nth[:, None] * STRIDE - OVERLAP + np.arange(WINDOW)
    real = (at >= 0) & (at < n[text][:, None])
    place = np.where(real, at, 0) + starts[:-1][text][:, None]
    return ids[place], real, ids[place + 1][:, OVERLAP:], real[:, OVERLAP:], text


def flatten(w: dict) -> bytes:
    return b"".join(w[n].astype(np.float32).tobytes() for n in NAMES)


def unflatten(raw: bytes) -> dict:
    like, out, at = fresh(), {}, 0
    x = np.frombuffer(raw, np.float32)
    for n in NAMES:
        size = like[n].size
        out[n] = x[at : at + size].reshape(like[n].shape).copy()
        at += size
    return out

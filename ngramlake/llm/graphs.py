"""The two inner loops of ``attention`` as graphs of onnxruntime, about half the processor time of numpy.

The same sums, in single precision too; ``attention`` keeps the numpy forms, which are the
reference in the tests and are used where onnxruntime is not installed.  A graph is written
here as the few protocol-buffer fields it needs, so no further package is asked for.  One
difference in form: the gradient of the logits is not made as a table; what the goals add to
it is a row of ``u`` for each goal.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

from . import attention as att

MS = "com.microsoft"
FLOAT, LONG = 1, 7
#: Windows worked on at once: a batch of training.
PART = 320


# ------------------------------------------------------------------ protocol buffers
def _number(n: int) -> bytes:
    out = bytearray()
    n &= (1 << 64) - 1
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes([*out, n])


def _field(tag: int, v: int | str | bytes) -> bytes:
    if isinstance(v, int):
        return _number(tag << 3) + _number(v)
    v = v.encode() if isinstance(v, str) else v
    return _number(tag << 3 | 2) + _number(len(v)) + v


def _node(op: str, ins: str, outs: str, domain: str = "", **attributes: int | str) -> bytes:
    got = [_field(1, x) for x in ins.split()] + [_field(2, x) for x in outs.split()] + [_field(4, op), _field(7, domain)]
    kind = lambda v: _field(3, v) + _field(20, 2) if isinstance(v, int) else _field(4, v) + _field(20, 3)
    return b"".join(got + [_field(5, _field(1, k) + kind(v)) for k, v in attributes.items()])


def _value(name: str, kind: int, rank: int) -> bytes:
    dims = b"".join(_field(1, _field(2, f"{name}{i}")) for i in range(rank))
    return _field(1, name) + _field(2, _field(1, _field(1, kind) + _field(2, dims)))


def _constant(name: str, x: np.ndarray) -> bytes:
    return b"".join(_field(1, d) for d in x.shape) + _field(2, LONG if x.dtype == np.int64 else FLOAT) + _field(8, name) + _field(9, x.tobytes())


def _session(nodes: list[bytes], ins: dict[str, tuple[int, int]], outs: dict[str, int]):
    import onnxruntime

    ints = {"first": [att.OVERLAP], "last": [att.WINDOW], "along": [1], "end": [-1], "none": [0], "flat": [-1, att.DIM], "late_rows": [-1, att.STRIDE, att.DIM], "all_rows": [-1, att.WINDOW, att.DIM],
            "ahead": [0, att.OVERLAP, 0, 0, 0, 0], "column": [-1, 1]}
    late = att._LATE[att.OVERLAP :]
    masks = np.stack([late, late | (np.arange(att.WINDOW) < att.OVERLAP)])  # of any window, and of a text's first
    zeros = {"no_goal": att.CLASSES + 1, "no_class": att.CLASSES, "no_hash": att.HASHED}
    fixed = [_constant(k, np.array(v, np.int64)) for k, v in ints.items()] + [_constant(k, np.zeros((n, att.DIM), np.float32)) for k, n in zeros.items()]
    fixed.append(_constant("masks", np.where(masks, np.float32(-1e9), np.float32(0))))
    graph = b"".join(_field(1, n) for n in nodes) + _field(2, "g") + b"".join(_field(5, c) for c in fixed)
    graph += b"".join(_field(11, _value(k, *v)) for k, v in ins.items()) + b"".join(_field(12, _value(k, FLOAT, n)) for k, n in outs.items())
    model = _field(1, 8) + _field(7, graph) + _field(8, _field(1, "") + _field(2, 17)) + _field(8, _field(1, MS) + _field(2, 1))
    how = onnxruntime.SessionOptions()
    how.intra_op_num_threads = how.inter_op_num_threads = 1
    how.enable_mem_pattern = False  # sizes of batches differ, each would keep a pattern
    how.log_severity_level = 3
    return onnxruntime.InferenceSession(model, how, providers=["CPUExecutionProvider"])


# ------------------------------------------------------------------ the graphs
INPUTS = {"x0": (FLOAT, 2), "kind": (LONG, 1), "to": (LONG, 1), "by_place": (FLOAT, 2), **{n: (FLOAT, 2) for n in "qkvou"}, "b": (FLOAT, 1)}


def _forward() -> list[bytes]:
    """Up to the exponentials of the logits and the logarithms of their totals."""
    return [
        _node("Reshape", "x0 all_rows", "x1"), _node("Add", "x1 by_place", "x"), _node("Slice", "x first last along", "late"),
        _node("MatMul", "x k", "keys"), _node("MatMul", "x v", "values"), _node("MatMul", "late q", "asks"),
        _node("FusedMatMul", "asks keys", "s0", MS, transB=1), _node("Gather", "masks kind", "mask"), _node("Add", "s0 mask", "s"), _node("Softmax", "s", "a"),
        _node("MatMul", "a values", "z"), _node("MatMul", "z o", "h0"), _node("Add", "late h0", "h1"), _node("Reshape", "h1 flat", "h"),
        _node("Gemm", "h u b", "y"), _node("Exp", "y", "e"), _node("ReduceSum", "e along", "total"), _node("Log", "total", "of_all"), _node("Reshape", "to column", "to_rows"),
    ]


@lru_cache(maxsize=1)
def _scoring():
    return _session([*_forward(), _node("GatherElements", "y to_rows", "hit", axis=1), _node("Sub", "hit of_all", "p")], INPUTS, {"p": 2})


@lru_cache(maxsize=1)
def _training():
    """``share``: each goal's share of the loss; ``goals``: that share of its class's row of ``u``."""
    flat = lambda n: _node("Reshape", f"{n} flat", f"f_{n}")
    turned = lambda a, b, out: _node("FusedMatMul", f"{a} {b}", out, MS, transA=1)
    across = lambda a, b, out: _node("FusedMatMul", f"{a} {b}", out, MS, transB=1)
    back = [
        # logits: e times r, less the share at the goal
        _node("Div", "share total", "r"), _node("Mul", "e r", "er"), across("er", "u", "f0"), _node("Sub", "f0 goals", "fh"),
        turned("h", "er", "g_u"), _node("ReduceSum", "er none", "g_b"), _node("ScatterND", "no_goal to_rows h", "at_goals", reduction="add"),
        flat("z"), turned("f_z", "fh", "g_o"), across("fh", "o", "dz0"), _node("Reshape", "dz0 late_rows", "dz"),
        # shares of attention
        across("dz", "values", "ds0"), _node("Mul", "dz z", "dot0"), _node("ReduceSum", "dot0 end", "dot"), _node("Sub", "ds0 dot", "ds1"), _node("Mul", "ds1 a", "ds"),
        turned("ds", "asks", "dk"), turned("a", "dz", "dv"), _node("MatMul", "ds keys", "dq"), *map(flat, ("dk", "dv", "dq", "x", "late")),
        turned("f_late", "f_dq", "g_q"), turned("f_x", "f_dk", "g_k"), turned("f_x", "f_dv", "g_v"),
        # inputs
        across("f_dk", "k", "dx0"), across("f_dv", "v", "dx1"), _node("Add", "dx0 dx1", "dx2"), _node("Reshape", "dx2 all_rows", "dx3"),
        across("f_dq", "q", "dl0"), _node("Add", "dl0 fh", "dl1"), _node("Reshape", "dl1 late_rows", "dl2"), _node("Pad", "dl2 ahead", "dl"), _node("Add", "dx3 dl", "dx"),
        _node("ReduceSum", "dx none", "g_by_place", keepdims=0), flat("dx"), _node("Reshape", "own column", "own_rows"), _node("Reshape", "hashed column", "hashed_rows"),
        _node("ScatterND", "no_class own_rows f_dx", "g_by_class", reduction="add"), _node("ScatterND", "no_hash hashed_rows f_dx", "g_by_hash", reduction="add"),
    ]
    more = {"share": (FLOAT, 2), "goals": (FLOAT, 2), "own": (LONG, 1), "hashed": (LONG, 1)}
    return _session(_forward() + back, INPUTS | more, {"of_all": 2, "at_goals": 2, **{f"g_{n}": 2 for n in att.NAMES}})


def _feeds(w: dict, own: np.ndarray, hashed: np.ndarray, real: np.ndarray, to: np.ndarray) -> dict:
    """Places are not real before a text (all or none of the first ones) and behind it, where
    nothing that is asked for sees them."""
    x = np.take(w["by_class"], own, 0)
    x += np.take(w["by_hash"], hashed, 0)
    return {n: w[n] for n in ("by_place", "k", "v", "o", "u", "b")} | {"q": w["q"] * np.float32(1 / math.sqrt(att.DIM)), "x0": x, "kind": 1 - real[:, 0].astype(np.int64), "to": to}


def class_log_probs(w: dict, ids: np.ndarray, real: np.ndarray, goal: np.ndarray, of: np.ndarray) -> np.ndarray:
    flat = ids.ravel()
    p = _scoring().run(["p"], _feeds(w, np.take(of, flat), flat % att.HASHED, real, np.take(of, goal.ravel())))[0]
    return p.reshape(goal.shape) if np.isfinite(p).all() else att.class_log_probs(w, ids, real, goal, of)


def gradients(w: dict, ids: np.ndarray, real: np.ndarray, goal: np.ndarray, use: np.ndarray, of: np.ndarray, n: int) -> tuple[float, dict]:
    flat, one = ids.ravel(), np.float32(1 / n)
    own, hashed, to = np.take(of, flat), flat % att.HASHED, np.where(use, np.take(of, goal), att.CLASSES).ravel()
    rows = np.concatenate([w["u"].T * one, np.zeros((1, att.DIM), np.float32)])  # nothing for a goal out of use
    share = use.reshape(-1, 1) * one
    run = _training()
    names = [x.name for x in run.get_outputs()]
    got = dict(zip(names, run.run(names, _feeds(w, own, hashed, real, to) | {"own": own, "hashed": hashed, "goals": np.take(rows, to, 0), "share": share}), strict=True))
    if not np.isfinite(got["of_all"]).all():
        return att._gradients(w, ids, real, goal, use, of, n)
    g = {k[2:]: x for k, x in got.items() if k.startswith("g_")}
    g["q"] *= np.float32(1 / math.sqrt(att.DIM))  # the graph has it scaled
    hit, many = got["at_goals"][:-1].T * one, np.bincount(to, minlength=att.CLASSES + 1)[:-1].astype(np.float32) * one
    g["u"], g["b"] = g["u"] - hit, g["b"][0] - many
    return float(got["of_all"][:, 0] @ share[:, 0] - (hit * w["u"]).sum() - many @ w["b"]), g

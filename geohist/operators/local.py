"""The same methods inside one task, on dense NumPy matrices; draws use the same keys as the DataFrame operators."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd

from geohist.functions import budget
from geohist.functions.noise import gumbel_of, laplace_of


class Cut:
    """Split values of one node: a dense block with the split axis first."""

    def __init__(self, block: np.ndarray):
        self.block, (self.u, self.v) = block, block.shape
        self.rows = block.sum(axis=1)
        self.low = np.cumsum(self.rows)
        self.total = float(self.low[-1]) if self.u else 0.0

    def unevenness(self, k: int) -> float:
        a, b = self.block[:k], self.block[k:]
        out = np.abs(a - self.low[k - 1] / a.size).sum()
        return float(out + (np.abs(b - (self.total - self.low[k - 1]) / b.size).sum() if b.size else 0.0))


def choose(cut: Cut, method: str, eps: float, secret: str, tree: str, node: int, rounds: int, allow_no_split: bool) -> tuple[int, int]:
    """(k, evaluations) of one node; k = extent leaves it whole."""
    u = cut.u
    last = u + 1 if allow_no_split else u
    if method == "midpoint":
        return 1 + (u - 1) // 2, 0
    if method == "exact":
        return min((cut.unevenness(k), k) for k in range(1, last))[1], last - 1
    if method == "exhaustive":
        scale = 2.0 * (last - 1) / eps
        return min((cut.unevenness(k) + laplace_of(scale, secret, tree, "split", node, k), k) for k in range(1, last))[1], last - 1
    if method == "exponential_unevenness":
        return min((cut.unevenness(k) * eps / 4.0 - gumbel_of(secret, tree, "rank", node, k), k) for k in range(1, u))[1], u - 1
    if method == "em_median":
        return min((abs(2 * cut.low[k - 1] - cut.total) * eps / 2.0 - gumbel_of(secret, tree, "rank", node, k), k) for k in range(1, u))[1], u - 1
    if method == "noisy_mean":
        s = float((np.arange(1, u + 1) * cut.rows).sum()) + laplace_of(u * 2 / eps, secret, tree, "mean", node, "sum")
        n = cut.total + laplace_of(2 / eps, secret, tree, "mean", node, "count")
        x = s / max(n, 1.0)
        return int(max(1, min(u - 1, math.copysign(math.floor(abs(x) + 0.5), x)))), 2
    if method != "searched":
        raise ValueError(method)
    scale = 2.0 * (2 * rounds + 1) / eps if eps else 0.0
    known: dict[int, float] = {}

    def value(k: int) -> float:
        if k not in known:
            known[k] = cut.unevenness(k) + (laplace_of(scale, secret, tree, "split", node, k) if scale else 0.0)
        return known[k]

    lo, hi, k = 1, u, 1 + (u - 1) // 2
    value(k)
    for _ in range(rounds):
        a, b = lo + (k - lo) // 2, k + (hi - k) // 2
        va, vk, vb = value(a), value(k), value(b)
        if vk <= va and vk <= vb:
            lo, hi = a, b
        elif va <= vb:
            hi, k = k, a
        else:
            lo, k = k, b
    return k, len(known)


def grow(matrix: np.ndarray, height: int, method: str, eps: float, secret: str, tree: str, rounds: int = 3, rule: str = "even_x", allow_no_split: bool = False, first: tuple = (1, 0, 0)) -> list[tuple]:
    """Nodes (tree, node, height, axis, x0, x1, y0, y1, split_at, cnt, evals) below a node; matrix[x, y] is its block."""
    node0, ox, oy = first
    out, stack = [], [(node0, height, 0, matrix.shape[0], 0, matrix.shape[1])]
    while stack:
        node, h, x0, x1, y0, y1 = stack.pop()
        axis = h % 2 if rule == "even_x" else (h + 1) % 2
        block = matrix[x0:x1, y0:y1]
        count, at, evals = int(round(float(block.sum()))), None, 0
        if h and (x1 - x0 if axis == 0 else y1 - y0) > 1:
            k, evals = choose(Cut(block if axis == 0 else block.T), method, eps, secret, tree, node, rounds, allow_no_split)
            if k < (x1 - x0 if axis == 0 else y1 - y0):
                at = (x0 if axis == 0 else y0) + k
                if axis == 0:
                    stack += [(2 * node, h - 1, x0, at, y0, y1), (2 * node + 1, h - 1, at, x1, y0, y1)]
                else:
                    stack += [(2 * node, h - 1, x0, x1, y0, at), (2 * node + 1, h - 1, x0, x1, at, y1)]
        shown = None if at is None else at + (ox if axis == 0 else oy)
        out.append((tree, node, h, axis, x0 + ox, x1 + ox, y0 + oy, y1 + oy, shown, count, evals))
    return out


COLUMNS = ["tree_id", "node_id", "height", "axis", "x0", "x1", "y0", "y1", "split_at", "cnt", "evals"]


def subtree(rows: pd.DataFrame, method: str, eps: float, secret: str, rounds: int, rule: str, allow_no_split: bool) -> pd.DataFrame:
    """A task's group: the columns of one node beside each of its cells."""
    n = rows.iloc[0]
    x0, x1, y0, y1 = (int(n[c]) for c in ("x0", "x1", "y0", "y1"))
    block = np.zeros((x1 - x0, y1 - y0))
    full = rows[rows["cell_cnt"].notna()]
    block[full["cx"].to_numpy(int) - x0, full["cy"].to_numpy(int) - y0] = full["cell_cnt"].to_numpy(float)
    out = pd.DataFrame(grow(block, int(n["height"]), method, eps, secret, str(n["tree_id"]), rounds, rule, allow_no_split, (int(n["node_id"]), x0, y0)), columns=COLUMNS)
    out["split_at"] = out["split_at"].astype("Int32")
    return out


def released(nodes: list[tuple], parts: list[float], eps_data: float, secret: str, min_count: float | None, min_cells: int | None, strategy: str = "pruned") -> list[tuple]:
    """(x0, x1, y0, y1, ncount) of the published leaves of one tree."""
    by = {n[1]: n for n in nodes}
    out, stack = [], [1]
    while stack:
        tree, node, h, _, x0, x1, y0, y1, at, cnt, _ = by[stack.pop()]
        leaf, cells = at is None, (x1 - x0) * (y1 - y0)
        if strategy == "leaves":
            if leaf:
                out.append((x0, x1, y0, y1, cnt + laplace_of(1 / eps_data, secret, tree, "final", node)))
            else:
                stack += [2 * node, 2 * node + 1]
            continue
        draw = cnt + laplace_of(1 / parts[h], secret, tree, "decide", node)
        stop = leaf or (strategy == "pruned" and ((min_count is not None and draw <= min_count) or (min_cells is not None and cells < min_cells)))
        if not stop:
            stack += [2 * node, 2 * node + 1]
        elif h and strategy == "pruned":
            out.append((x0, x1, y0, y1, cnt + laplace_of(1 / budget.remaining(parts, h), secret, tree, "final", node)))
        else:
            out.append((x0, x1, y0, y1, draw))
    return out


def smoothed(values: dict[int, float], variance: dict[int, float], fanout: int = 2) -> dict[int, float]:
    """Weighted least squares over a heap-numbered tree: children then sum to their parent.

    Estimates go up as means weighted by their certainty; on the way down each parent's surplus is shared by variance.
    """
    kids: dict[int, list[int]] = {}
    for i in values:
        p = i // 2 if fanout == 2 else (i + 2) // 4
        if i != 1 and p in values:
            kids.setdefault(p, []).append(i)
    z, s = {}, {}
    for i in sorted(values, reverse=True):
        y, v = values[i], variance[i]
        if i in kids:
            zc, sc = sum(z[c] for c in kids[i]), sum(s[c] for c in kids[i])
            z[i], s[i] = (y / v + zc / sc) / (1 / v + 1 / sc), 1 / (1 / v + 1 / sc)
        else:
            z[i], s[i] = y, v
    final = {1: z[1]}
    for i in sorted(kids):
        zc, sc = sum(z[c] for c in kids[i]), sum(s[c] for c in kids[i])
        for c in kids[i]:
            final[c] = z[c] + (final[i] - zc) * s[c] / sc
    return final


def blocks_to_cells(rects: list[tuple], nx: int, ny: int) -> np.ndarray:
    """Density of every cell from disjoint rectangles (x0, x1, y0, y1, ncount), each spread evenly."""
    d = np.zeros((nx + 1, ny + 1))
    if rects:
        a = np.array(rects, float)
        x0, x1, y0, y1 = (a[:, i].astype(int) for i in range(4))
        v = a[:, 4] / ((x1 - x0) * (y1 - y0))
        for x, y, sign in ((x0, y0, 1), (x1, y0, -1), (x0, y1, -1), (x1, y1, 1)):
            np.add.at(d, (x, y), sign * v)
    return d.cumsum(axis=0).cumsum(axis=1)[:nx, :ny]


def answers(density: np.ndarray, queries: np.ndarray) -> np.ndarray:
    """Sums over rectangles (x0, x1, y0, y1) by prefix sums."""
    p = np.zeros((density.shape[0] + 1, density.shape[1] + 1))
    p[1:, 1:] = density.cumsum(axis=0).cumsum(axis=1)
    x0, x1, y0, y1 = queries.T
    return p[x1, y1] - p[x0, y1] - p[x1, y0] + p[x0, y0]


def laplace_matrix(shape: tuple[int, int], scale: np.ndarray | float, secret: str, *key) -> np.ndarray:
    """Independent Laplace noise from a generator seeded by the key; for matrices too large to key each cell in a task."""
    seed = int(laplace_seed(secret, *key))
    return np.random.default_rng(seed).laplace(0, 1, shape) * scale


def laplace_seed(secret: str, *key) -> int:
    import hashlib

    return int.from_bytes(hashlib.sha256("/".join(map(str, (secret, *key, "matrix"))).encode()).digest()[:8], "big")


def haar(m: np.ndarray) -> np.ndarray:
    """Haar coefficients along the first axis (a power of two): entry 0 the mean, then details from coarse to fine."""
    out, a, n = np.empty_like(m), m, len(m)
    while n > 1:
        low, high = a[0::2], a[1::2]
        n //= 2
        out[n : 2 * n] = (low - high) / 2
        a = (low + high) / 2
    out[0] = a[0]
    return out


def unhaar(c: np.ndarray) -> np.ndarray:
    a, n = c[:1].copy(), 1
    while n < len(c):
        d = c[n : 2 * n]
        b = np.empty((2 * n, *c.shape[1:]))
        b[0::2], b[1::2] = a + d, a - d
        a, n = b, 2 * n
    return a


def haar_weights(n: int) -> np.ndarray:
    """Cells that a coefficient spans."""
    w = np.full(n, float(n))
    i = 1
    while i < n:
        w[i : 2 * i] = n / i
        i *= 2
    return w


def wavelet(matrix: np.ndarray, eps: float, secret: str, tree: str) -> np.ndarray:
    """Noisy cells by noise on tensor Haar coefficients, less on those that many cells share."""
    nx, ny = (1 << (n - 1).bit_length() for n in matrix.shape)
    m = np.zeros((nx, ny))
    m[: matrix.shape[0], : matrix.shape[1]] = matrix
    c = haar(haar(m).T).T
    rho = (1 + math.log2(nx)) * (1 + math.log2(ny))
    c = c + laplace_matrix(c.shape, rho / (eps * haar_weights(nx)[:, None] * haar_weights(ny)[None, :]), secret, tree, "coef")
    return unhaar(unhaar(c.T).T)[: matrix.shape[0], : matrix.shape[1]]

"""Sums of distances over all pairs of rows of two features, in near linear time. No Spark in here.

Rows lie in square cells, cells in cells of twice the width, and so on. Pairs from cells that touch are summed one by
one. For all others the distance is smooth over the two cells, and each cell stands for its rows by weights on ``NODES``
Chebyshev nodes a side; at 14 nodes the relative error of a sum is some 1e-12, as that of adding floats. No row is left out.
"""

from __future__ import annotations

import numpy as np

NODES = 14
#: rows that a row finds in its own cell, on the average, at the finest level
CROWD = 200
#: cells a side that integers can name
REACH = 2**30
#: halvings of the whole width down to the smallest cells, where rows are spread over tasks
DEEPEST = 26
#: halvings from a task's tile to its smallest cells
STEPS = 4

_K = np.arange(NODES)
_AT = np.cos((2 * _K + 1) * np.pi / (2 * NODES))


def _onto(t: np.ndarray) -> np.ndarray:
    """Interpolation weights of places ``t`` in [-1, 1], (places, nodes)."""
    high = np.cos(np.arccos(np.clip(t, -1, 1))[:, None] * _K)
    nodes = np.cos(np.arccos(_AT)[:, None] * _K) * np.where(_K, 2.0, 1.0) / NODES
    return high @ nodes.T


#: from the nodes of a cell's lower and upper half to its own
_HALVES = [_onto((_AT + s) / 2) for s in (-1, 1)]


def _code(c: np.ndarray) -> np.ndarray:
    """One integer per cell, in the order of its two numbers."""
    return (c[:, 0] << 32) + c[:, 1]


def _shift_kernel(a: int, b: int) -> np.ndarray:
    """Distances of the nodes of a cell of half-width 1 from those of the cell ``a, b`` cells further."""
    dx, dy = _AT[:, None] - _AT[None] - 2 * a, _AT[:, None] - _AT[None] - 2 * b
    return np.sqrt((dx**2)[:, None, :, None] + (dy**2)[None, :, None, :]).reshape(NODES**2, NODES**2)


_KERNELS: dict[tuple[int, int], np.ndarray] = {}


class _Rows:
    """Rows in order of their cells, with each cell's weights at its own level and above."""

    def __init__(self, x: np.ndarray, low: np.ndarray, width: float) -> None:
        cell = np.floor((x - low) / width).astype(np.int64)
        code = _code(cell)
        order = np.argsort(code, kind="stable")
        self.x, code, cell = x[order], code[order], cell[order]
        first = np.nonzero(np.concatenate([[True], code[1:] != code[:-1]]))[0]
        self.edges = np.append(first, len(x))
        self.cells, self.codes = [cell[first]], [code[first]]
        inside = 2 * ((self.x - low) / width - cell) - 1
        u, v = _onto(inside[:, 0]), _onto(inside[:, 1])
        self.weights = [np.array([u[a:b].T @ v[a:b] for a, b in zip(self.edges, self.edges[1:], strict=False)])]

    def level(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cells, codes and weights at ``k`` doublings of the width."""
        while len(self.cells) <= k:
            cell, weight = self.cells[-1], self.weights[-1]
            above, half = cell >> 1, cell & 1
            codes, first, to = np.unique(_code(above), return_index=True, return_inverse=True)
            out = np.zeros((len(codes), NODES, NODES))
            for a in (0, 1):
                for b in (0, 1):
                    mine = (half[:, 0] == a) & (half[:, 1] == b)  # one cell at most in each cell above
                    out[to[mine]] += _HALVES[a].T @ weight[mine] @ _HALVES[b]
            self.cells.append(above[first])
            self.codes.append(codes)
            self.weights.append(out)
        return self.cells[k], self.codes[k], self.weights[k]


class Field:
    """Sums of distances from any rows to the rows ``x``; what far cells contribute to a place is kept."""

    def __init__(self, x: np.ndarray) -> None:
        self.low = x.min(0)
        span, self.width = float((x.max(0) - self.low).max()), 0.0
        if np.isfinite(span) and span > 0:
            self.width = width = span
            for _ in range(24):
                counts = np.unique(_code(np.floor((x - self.low) / width).astype(np.int64)), return_counts=True)[1]
                self.width = width
                if (counts.astype(float) ** 2).sum() <= CROWD * len(x):
                    break
                width /= 2
            self.rows = _Rows(x, self.low, self.width)
            self.known: list[tuple[np.ndarray, np.ndarray]] = []

    def reaches(self, y: np.ndarray) -> bool:
        """Whether the rows of ``y`` can be named by cells."""
        return self.width > 0 and bool((np.abs(y - self.low) < self.width * REACH).all())

    def total(self, y: np.ndarray) -> float:
        rows = _Rows(y, self.low, self.width)
        total, k = self._near(rows), 0
        while True:
            cells, codes, weights = rows.level(k)
            others = self.rows.level(k)[0]
            if min(cells.min(), others.min()) >= -1 and max(cells.max(), others.max()) <= 0:
                return total
            total += float((weights.reshape(len(cells), -1) * self._far(k, cells, codes)).sum())
            k += 1

    def _near(self, rows: _Rows) -> float:
        """Pairs from cells that touch; the three cells of a column lie side by side."""
        cells, codes, mine, total = rows.cells[0], rows.codes[0], self.rows, 0.0
        spans = []
        for a in (-1, 0, 1):
            low, high = codes + (a << 32) - 1, codes + (a << 32) + 1
            spans.append((mine.edges[np.searchsorted(mine.codes[0], low)], mine.edges[np.searchsorted(mine.codes[0], high, "right")]))
        xs, ys = np.ascontiguousarray(mine.x.T), np.ascontiguousarray(rows.x.T)
        for k in range(len(cells)):
            p, q = ys[0, rows.edges[k] : rows.edges[k + 1], None], ys[1, rows.edges[k] : rows.edges[k + 1], None]
            for low, high in spans:
                for at in range(low[k], high[k], 4096):
                    to = min(at + 4096, high[k])
                    for i in range(0, len(p), 256):
                        dx, dy = p[i : i + 256] - xs[0, at:to], q[i : i + 256] - xs[1, at:to]
                        dx *= dx
                        dy *= dy
                        dx += dy
                        total += float(np.sqrt(dx, out=dx).sum())
        return total

    def _far(self, k: int, cells: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Per cell the sums, at its nodes, over the cells of its level that do not touch it, whose cells above do."""
        while len(self.known) <= k:
            self.known.append((np.zeros(0, np.int64), np.zeros((0, NODES**2))))
        have, sums = self.known[k]
        new = ~np.isin(codes, have)
        if new.any():
            found = self._sums(k, cells[new], codes[new])
            have, sums = np.concatenate([have, codes[new]]), np.concatenate([sums, found])
            order = np.argsort(have)
            have, sums = self.known[k] = have[order], sums[order]
        return sums[np.searchsorted(have, codes)]

    def _sums(self, k: int, cells: np.ndarray, codes: np.ndarray) -> np.ndarray:
        _, others, weights = self.rows.level(k)
        out, half = np.zeros((len(cells), NODES**2)), self.width * 2.0**k / 2
        flat = weights.reshape(len(others), -1)
        for a in range(-3, 4):
            for b in range(-3, 4):
                if max(abs(a), abs(b)) < 2:
                    continue
                far = np.abs(((cells + [a, b]) >> 1) - (cells >> 1)).max(1) <= 1
                want = codes + (a << 32) + b
                at = np.minimum(np.searchsorted(others, want), len(others) - 1)
                met = np.nonzero(far & (others[at] == want))[0]
                if len(met):
                    if (a, b) not in _KERNELS:
                        _KERNELS[a, b] = _shift_kernel(a, b)
                    out[met] += flat[at[met]] @ _KERNELS[a, b].T
        return out * half


# ----------------------------------------------------------- the same, tile by tile


def summed(p: np.ndarray, q: np.ndarray) -> float:
    """Summed distances of all pairs of a row of ``p`` and one of ``q``, of any number of features."""
    shift, total = p.mean(0), 0.0
    p, q = p - shift, q - shift
    pp, qq = (p * p).sum(1), (q * q).sum(1)
    # products small enough to stay in their own thread
    high, wide = 128, max(32, 250_000 // (128 * p.shape[1]))
    for i in range(0, len(p), high):
        for j in range(0, len(q), wide):
            ends = pp[i : i + high, None] + qq[None, j : j + wide]
            sq = p[i : i + high] @ q[j : j + wide].T
            sq *= -2.0
            sq += ends
            # rows that coincide: the products cancel to rounding noise
            ends *= 1e-12
            sq[sq < ends] = 0.0
            total += float(np.sqrt(sq, out=sq).sum())
    return total


def leaves(x: np.ndarray, w: np.ndarray, low: np.ndarray, width: float) -> tuple[np.ndarray, np.ndarray]:
    """The cells of weighted rows and the cells' weights."""
    crowd = Crowd(x, w, low, width)
    inside = 2 * ((crowd.x - low) / width - np.repeat(crowd.cells, np.diff(crowd.edges), axis=0)) - 1
    u, v = _onto(inside[:, 0]) * crowd.w[:, None], _onto(inside[:, 1])
    return crowd.cells, np.array([u[a:b].T @ v[a:b] for a, b in zip(crowd.edges, crowd.edges[1:], strict=False)])


def above(cells: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells of twice the width and their weights."""
    half = cells & 1
    _, first, to = np.unique(_code(cells >> 1), return_index=True, return_inverse=True)
    out = np.zeros((len(first), NODES, NODES))
    for a in (0, 1):
        for b in (0, 1):
            mine = (half[:, 0] == a) & (half[:, 1] == b)  # one cell at most in each cell above
            out[to[mine]] += _HALVES[a].T @ weights[mine] @ _HALVES[b]
    return cells[first] >> 1, out


def apart(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray], half: float) -> float:
    """Summed distances over pairs of cells that do not touch, whose cells above do; ``half``: half a cell's width."""
    cells, codes = one[0], _code(two[0])
    if not len(cells) or not len(codes):
        return 0.0
    order = np.argsort(codes)
    codes, mine, theirs, total = codes[order], one[1].reshape(len(cells), -1), two[1].reshape(len(codes), -1), 0.0
    for a in range(-3, 4):
        for b in range(-3, 4):
            if max(abs(a), abs(b)) < 2:
                continue
            far = np.abs(((cells + [a, b]) >> 1) - (cells >> 1)).max(1) <= 1
            want = _code(cells + [a, b])
            at = np.minimum(np.searchsorted(codes, want), len(codes) - 1)
            met = np.nonzero(far & (codes[at] == want))[0]
            if len(met):
                if (a, b) not in _KERNELS:
                    _KERNELS[a, b] = _shift_kernel(a, b)
                total += float(((theirs[order[at[met]]] @ _KERNELS[a, b].T) * mine[met]).sum())
    return total * half


def tower(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray], half: float) -> float:
    """``apart`` over the level of both sides' cells and all above."""
    total = 0.0
    while min(one[0].min(), two[0].min()) < -1 or max(one[0].max(), two[0].max()) > 0:
        total += apart(one, two, half)
        one, two, half = above(*one), above(*two), 2 * half
    return total


class Crowd:
    """Weighted rows in the order of their cells."""

    def __init__(self, x: np.ndarray, w: np.ndarray, low: np.ndarray, width: float) -> None:
        cell = np.floor((x - low) / width).astype(np.int64)
        code = _code(cell)
        order = np.argsort(code, kind="stable")
        code, self.x, self.w = code[order], x[order], w[order]
        self.plain = bool((w == 1).all())
        first = np.nonzero(np.concatenate([[True], code[1:] != code[:-1]]))[0]
        self.edges, self.cells, self.codes = np.append(first, len(x)), cell[order][first], code[first]

    def touching(self, other: Crowd) -> float:
        """Summed distances over pairs from cells that touch; the three cells of a column lie side by side."""
        total, spans = 0.0, []
        for a in (-1, 0, 1):
            low, high = self.codes + (a << 32) - 1, self.codes + (a << 32) + 1
            spans.append((other.edges[np.searchsorted(other.codes, low)], other.edges[np.searchsorted(other.codes, high, "right")]))
        (xs, ys), (ps, qs) = np.ascontiguousarray(other.x.T), np.ascontiguousarray(self.x.T)
        for k in range(len(self.cells)):
            mine = slice(self.edges[k], self.edges[k + 1])
            p, q, w = ps[mine, None], qs[mine, None], self.w[mine]
            for low, high in spans:
                for at in range(low[k], high[k], 2048):
                    to = slice(at, min(at + 2048, high[k]))
                    for i in range(0, len(p), 128):
                        dx, dy = p[i : i + 128] - xs[to], q[i : i + 128] - ys[to]
                        dx *= dx
                        dy *= dy
                        dx += dy
                        np.sqrt(dx, out=dx)
                        if not other.plain:
                            dx *= other.w[to]
                        total += float(w[i : i + 128] @ dx.sum(1))
        return total

"""Rows that meet all rows of a map, in Arrow tasks.

One side, a few numbers a row, is sent to every task; the other passes in chunks, tile by tile, so pairs
live in a worker's cache and only what they add up to, or their nearest, leaves the task. Time is
quadratic, memory and traffic are not.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: rows of the passing side and of the sent side that meet at once: their pairs fit a core's cache
CHUNK, TILE = 64, 1024
#: rows that are sorted together before they look for their nearest
MANY = 10_000


def arrays(batch) -> list[np.ndarray]:
    """A batch's columns; numbers that are missing become NaN."""
    return [c.to_numpy(zero_copy_only=False) if not c.null_count else c.cast(pa.float64()).to_numpy(zero_copy_only=False) for c in batch.columns]


def sent(rows: DataFrame, order: list[str]) -> tuple[Broadcast, int]:
    """The columns of ``rows`` in the order of the given ones, on every executor, and their number of rows."""
    table = rows.toArrow().combine_chunks()
    columns = [c.combine_chunks() for c in table.columns]
    # an empty or chunked column is one array either way
    flat = arrays(pa.table(columns, names=table.column_names))
    at = np.lexsort([flat[table.column_names.index(c)] for c in reversed(order)])
    return rows.sparkSession.sparkContext.broadcast([np.ascontiguousarray(c[at]) for c in flat]), len(at)


def spread(rows: DataFrame, partners: int) -> DataFrame:
    """``rows`` dealt over tasks: some for each core, and more where there are many pairs."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(int(max(3 * cores, min(partners // 5000, 2000))))


def chunks(batches: Iterator[pa.RecordBatch], size: int = CHUNK) -> Iterator[list[np.ndarray]]:
    for batch in batches:
        for k in range(0, batch.num_rows, size):
            yield arrays(batch.slice(k, size))


def squares(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """Squared distances of all pairs, from the differences of each feature."""
    total = None
    for x, y in zip(a, b, strict=True):
        gap = x[:, None] - y[None]
        gap *= gap
        total = gap if total is None else np.add(total, gap, out=total)
    return total


class Nearest:
    """The ``k`` nearest rows of a side sorted by key: tiles in the order of the first feature, of which a row meets
    those that reach into its distance to the ``k``-th nearest so far."""

    def __init__(self, keys: np.ndarray, y: list[np.ndarray], k: int) -> None:
        self.keys, self.k = keys, k
        self.at = np.argsort(y[0], kind="stable")
        self.y = [np.ascontiguousarray(c[self.at]) for c in y]
        self.starts = np.arange(0, len(keys), TILE)
        self.low, self.high = self.y[0][self.starts], self.y[0][np.minimum(self.starts + TILE, len(keys)) - 1]
        self.gaps = any(np.isnan(c).any() for c in y)

    def of(self, own: np.ndarray | None, x: list[np.ndarray]) -> np.ndarray:
        """Places of the nearest of each row of ``x`` in order, ties by place; -1 where there are fewer. ``own``: keys of
        ``x``, whose equals are left out. Rows without a place come last."""
        out = np.full((len(x[0]), self.k), -1, np.int64)
        order = np.argsort(x[0], kind="stable")
        for start in range(0, len(order), CHUNK):
            mine = order[start : start + CHUNK]
            out[mine] = self._chunk(own[mine] if own is not None else None, [c[mine] for c in x])
        return out

    def _chunk(self, own: np.ndarray | None, x: list[np.ndarray]) -> np.ndarray:
        n, k = len(x[0]), self.k
        best, where = np.full((n, k), np.inf), np.full((n, k), -1, np.int64)
        gaps = self.gaps or any(np.isnan(c).any() for c in x)
        middle = x[0][n // 2]
        for t in np.argsort(np.maximum(np.maximum(self.low - middle, middle - self.high), 0), kind="stable"):
            # not (apart > reach): rows without a place meet all
            apart = np.maximum(self.low[t] - x[0], x[0] - self.high[t]) * (1 - 1e-12)
            rows = np.nonzero(~(apart > best[:, -1]))[0]
            if not len(rows):
                continue
            cut = slice(self.starts[t], self.starts[t] + TILE)
            places = self.at[cut]
            sq = squares([c[rows] for c in x], [c[cut] for c in self.y])
            if gaps:
                np.nan_to_num(sq, copy=False, nan=1e300, posinf=1e300)
            if own is not None:
                keys = self.keys[places]
                mine, found = own[rows], np.nonzero(np.isin(keys, own[rows]))[0]
                for j in found:
                    sq[mine == keys[j], j] = np.inf
            reach = best[rows, -1]
            if np.isinf(reach).any() and len(places) > k:
                reach = np.minimum(reach, np.sqrt(np.partition(sq, k - 1, axis=1)[:, k - 1]))
            # roots of different squares may be equal: a little more passes, the roots decide
            r, c = np.nonzero(sq <= np.minimum(reach * reach * (1 + 1e-14), 1e301)[:, None])
            d, p = np.sqrt(sq[r, c]), places[c]
            r = rows[r]
            keep = (d < best[r, -1]) | ((d == best[r, -1]) & (p < where[r, -1]))
            r, d, p = r[keep], d[keep], p[keep]
            touched = np.unique(r)
            if not len(touched):
                continue
            r, d = np.concatenate([np.repeat(touched, k), r]), np.concatenate([best[touched].ravel(), d])
            p = np.concatenate([where[touched].ravel(), p])
            by = np.lexsort([p, d, r])
            r, d, p = r[by], d[by], p[by]
            take = (np.searchsorted(r, touched)[:, None] + np.arange(k)[None]).ravel()
            best[touched], where[touched] = d[take].reshape(-1, k), p[take].reshape(-1, k)
        return where


def sums(rows: DataFrame, run: Callable[[list[np.ndarray]], np.ndarray], size: int) -> np.ndarray:
    """``size`` numbers, added over all chunks of ``rows``."""

    def task(batches):
        total = np.zeros(size)
        for part in chunks(batches):
            total += run(part)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(size)), pa.array(total)], names=["k", "v"])

    found = {r["k"]: r["v"] for r in rows.mapInArrow(task, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).collect()}
    return np.array([found.get(k, 0.0) for k in range(size)])

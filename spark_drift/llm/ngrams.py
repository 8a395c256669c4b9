"""Hashed n-gram indicators of whole texts, and their compressed rows on the driver."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa

from spark_drift.llm.batches import mix64, slices, texts

BITS = 18
SIZE = 1 << BITS
#: bytes that belong to words: ASCII letters and all bytes of longer code points
LETTER = np.array([chr(b).isalpha() if b < 128 else True for b in range(256)])
_SALT = {"stem4": 0x9E3779B1, "stem6": 0x85EBCA77, "gram3": 0xC2B2AE3D, "gram5": 0x27D4EB2F, "again": 0x165667B1}


def _places(codes: np.ndarray, kind: str) -> np.ndarray:
    """Hashed places of n-gram codes, ``SIZE`` of them for all kinds together."""
    mixed = mix64(codes.astype(np.uint64) ^ np.uint64(_SALT[kind] << 32))
    return (mixed >> np.uint64(64 - BITS)).astype(np.int32)


def _grams(data: np.ndarray, n: int, at: np.ndarray | None = None) -> np.ndarray:
    """Codes of the n bytes from each position (from ``at`` where given)."""
    last = len(data) - n + 1
    out = np.zeros(last if at is None else len(at), dtype=np.uint64)
    for k in range(n):
        piece = data[k : k + last] if at is None else data[at + k]
        out = out << np.uint64(8) | piece.astype(np.uint64)
    return out


def distinct(places: np.ndarray) -> np.ndarray:
    """Sorted values without repeats."""
    places.sort()
    fresh = np.empty(len(places), dtype=bool)
    fresh[:1] = True
    np.not_equal(places[1:], places[:-1], out=fresh[1:])
    return places[fresh]


def _bytes(text: str) -> np.ndarray:
    return np.frombuffer(b" " + text.lower().encode() + b"      ", dtype=np.uint8)


def stem_indicators(text: str) -> np.ndarray:
    """Places of the first four and six bytes from each word's start, without repeats.

    A word's stem is found under whatever ending it has."""
    data = _bytes(text)
    letter = LETTER[data]
    starts = np.nonzero(letter[1:] & ~letter[:-1])[0] + 1
    if not len(starts):
        return np.zeros(0, np.int32)
    return distinct(np.concatenate([_places(_grams(data, 4, starts), "stem4"), _places(_grams(data, 6, starts), "stem6")]))


def phrase_indicators(text: str) -> np.ndarray:
    """Places of byte trigrams, of five-byte grams at word starts, and of the tenths
    that the share of repeated word pairs reaches, without repeats."""
    data = _bytes(text)
    blank = data <= 32
    starts = np.nonzero(~blank[1:] & blank[:-1])[0] + 1
    found = [_places(_grams(data, 3), "gram3"), _places(_grams(data, 5, starts), "gram5")]
    words = text.lower().split()
    if len(words) > 1:
        pairs = len(set(zip(words, words[1:], strict=False)))
        again = 10 * (len(words) - 1 - pairs) // (len(words) - 1)
        found.append(_places(np.arange(again + 1), "again"))
    return distinct(np.concatenate(found))


def feature_rows(kind: str):
    """``mapInArrow`` function for ``(y, text)`` rows: ``y`` and the indicator places."""
    make = stem_indicators if kind == "stems" else phrase_indicators

    def run(batches):
        for part in slices(batches, "text"):
            rows = [make(x) for x in texts(part)]
            offsets = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int32)
            values = np.concatenate(rows).astype(np.int32) if rows else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))], names=["y", "x"]
            )

    return run


class Rows:
    """Indicator rows in compressed form, in an order that does not depend on arrival."""

    def __init__(self, table: pa.Table) -> None:
        table = table.combine_chunks()
        y = table.column("y").to_numpy()
        x = table.column("x").combine_chunks()
        x = x.chunk(0) if isinstance(x, pa.ChunkedArray) else x
        starts = x.offsets.to_numpy().astype(np.int64)
        values = x.values.to_numpy().astype(np.int64)
        sizes = np.diff(starts)
        keys = np.array([zlib.crc32(values[a:b].tobytes()) for a, b in zip(starts, starts[1:], strict=False)], dtype=np.int64)
        order = np.lexsort([keys, sizes, y])
        self.y = y[order]
        self.values = np.concatenate([values[starts[k] : starts[k + 1]] for k in order]) if len(order) else values[:0]
        self.sizes = sizes[order]
        self.starts = np.concatenate([[0], np.cumsum(self.sizes)])

    def __len__(self) -> int:
        return len(self.y)

    def row(self, k: int) -> np.ndarray:
        return self.values[self.starts[k] : self.starts[k + 1]]

    def dot(self, weights: np.ndarray) -> np.ndarray:
        """Sum of the weights of each row's indicators."""
        # an empty row would make reduceat repeat a neighbour's value
        out = np.zeros(len(self))
        some = self.sizes > 0
        if some.any():
            out[some] = np.add.reduceat(weights[self.values], self.starts[:-1][some])
        return out

    def spread(self, per_row: np.ndarray) -> np.ndarray:
        """Sum over rows of ``per_row`` at each place (the transpose of ``dot``)."""
        return np.bincount(self.values, np.repeat(per_row, self.sizes), SIZE)

    def only(self, places: np.ndarray) -> None:
        """Forget all indicators but those where ``places`` is true."""
        keep = places[self.values]
        which = np.repeat(np.arange(len(self)), self.sizes)[keep]
        self.values = self.values[keep]
        self.sizes = np.bincount(which, minlength=len(self))
        self.starts = np.concatenate([[0], np.cumsum(self.sizes)])

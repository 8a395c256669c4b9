"""Language identification with hyperdimensional profiles.

Each letter has a random vector of +1 and -1. An n-gram's vector is the product
(binding) of its letters' vectors, each rotated (permuted) by its place; a document's
vector is the sum (bundle) of its n-grams' vectors; a language's prototype is the sum
of its documents' vectors brought to unit length. A document gets the language whose
prototype has the largest cosine with it, and that cosine, not below 0, as its score.

Letters are lower-cased; every run of other characters is one gap, which is a symbol
of its own, so n-grams also mark word starts and ends. Letters up to U+024F have
symbols of their own, the others share a few hundred by their code point.

Prototypes are fitted on at most ``per_language`` labelled documents of each
language, chosen by a digest of the id; prediction reads whole texts of all rows.

Edge cases: a text that is null or has no letters is ``und`` with score 0; equal
cosines go to the language first by code point; without labelled rows all is
``und``; repeated rows repeat; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.llm.batches import slices, texts

DIMENSIONS = 1024
GRAM = 3
SHARED = 256
OWN = 0x250
SYMBOLS = 1 + OWN + SHARED
PIECE = 1 << 18


def letter_vectors(dimensions: int = DIMENSIONS, seed: int = 7) -> np.ndarray:
    """+1/-1 rows per symbol; row 0 is the gap."""
    return np.random.Generator(np.random.PCG64(seed)).choice(np.array([-1, 1], np.int8), (SYMBOLS, dimensions))


class Profiler:
    """Texts to document vectors; symbol tables fill as code points are met."""

    def __init__(self, dimensions: int = DIMENSIONS) -> None:
        base = letter_vectors(dimensions)
        self.rotated = [np.roll(base, GRAM - 1 - k, axis=1) for k in range(GRAM)]
        self.dimensions = dimensions
        self.symbol = np.full(0x110000, -1, dtype=np.int16)
        self.known: dict[int, np.ndarray] = {}

    def symbols(self, text: str) -> np.ndarray:
        """Symbols of the lower-cased text, runs of non-letters as one gap (0)."""
        points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype="<u4")
        found = self.symbol[points]
        if (found < 0).any():
            for c in np.unique(points[found < 0]).tolist():
                letter = chr(c).isalpha()
                self.symbol[c] = (1 + (c if c < OWN else OWN + c % SHARED)) if letter else 0
            found = self.symbol[points]
        gap = found == 0
        gap[1:] &= found[:-1] == 0
        gap[:1] = False
        return found[~gap]

    def grams(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Distinct n-gram codes and their counts."""
        codes, counts = [], []
        tail = np.zeros(1, np.int16)
        for at in range(0, len(text), PIECE):
            s = np.concatenate([tail, self.symbols(text[at : at + PIECE])])
            if len(tail) and len(s) > len(tail) and s[len(tail)] == 0 and tail[-1] == 0:
                s = np.delete(s, len(tail))
            if at + PIECE >= len(text) and s[-1] != 0:
                s = np.append(s, np.int16(0))
            s = s.astype(np.int64)
            n = len(s) - GRAM + 1
            if n > 0:
                code = s[:n]
                for k in range(1, GRAM):
                    code = code * SYMBOLS + s[k : k + n]
                u, c = np.unique(code, return_counts=True)
                codes.append(u)
                counts.append(c)
            tail = s[-(GRAM - 1) :].astype(np.int16)
        if not codes:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        if len(codes) == 1:
            return codes[0], counts[0]
        u, where = np.unique(np.concatenate(codes), return_inverse=True)
        return u, np.bincount(where, np.concatenate(counts)).astype(np.int64)

    def gram_vectors(self, codes: np.ndarray) -> np.ndarray:
        out = None
        for k in range(GRAM):
            letter = codes // SYMBOLS ** (GRAM - 1 - k) % SYMBOLS
            part = self.rotated[k][letter]
            out = part if out is None else out * part
        return out

    def vectors(self, docs: list[str]) -> np.ndarray:
        """One float row per text; zero where there are no letters."""
        out = np.zeros((len(docs), self.dimensions), np.float32)
        for start in range(0, len(docs), 64):
            found = [self.grams(x) for x in docs[start : start + 64]]
            codes = np.unique(np.concatenate([u for u, _ in found])) if found else np.zeros(0, np.int64)
            for low in range(0, len(codes), 8192):
                some = codes[low : low + 8192]
                weights = np.zeros((len(found), len(some)), np.float32)
                for k, (u, c) in enumerate(found):
                    a, b = np.searchsorted(u, [some[0], some[-1] + 1])
                    weights[k, np.searchsorted(some, u[a:b])] = c[a:b]
                out[start : start + len(found)] += weights @ self.gram_vectors(some).astype(np.float32)
        return out


def unit(rows: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(rows, axis=1, keepdims=True)
    return np.divide(rows, size, out=np.zeros_like(rows), where=size > 0)


def fit_prototypes(labelled: DataFrame, per_language: int = 400, dimensions: int = DIMENSIONS) -> dict[str, np.ndarray]:
    """Unit prototype per language from ``(doc_id, text, lang)`` rows.

    At most about ``per_language`` rows of a language are used: those whose id
    digest lies below that share of the range.
    """
    labelled = labelled.where("lang is not null and text is not null")
    # one number per language comes to the driver, which holds a prototype of each anyway
    counts = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()
    if not counts:
        return {}
    limits = [(r["lang"], int(min(1.0, per_language / r["n"]) * (1 << 32))) for r in counts]
    below = F.element_at(F.create_map(*[F.lit(x) for pair in limits for x in pair]), F.col("lang"))
    draw = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit("language")), F.lit(1 << 32))
    chosen = labelled.where(draw < below).select("lang", "text")

    def bundle(batches):
        profiler, sums = Profiler(dimensions), {}
        for part in slices(batches, "text"):
            rows = unit(profiler.vectors(texts(part)))
            for lang, row in zip(part.column(0).to_pylist(), rows, strict=True):
                sums[lang] = sums.get(lang, 0) + row.astype(np.float64)
        if sums:
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(sums), pa.string()), pa.array([v.astype("<f8").tobytes() for v in sums.values()], pa.binary())],
                names=["lang", "bundle"],
            )

    # a partial bundle per task and language; the sums of one language meet in one task
    def total(key, table):
        rows = [np.frombuffer(x, "<f8") for x in table.column("bundle").to_pylist()]
        return pa.table({"lang": pa.array([key[0].as_py()], pa.string()), "bundle": pa.array([np.sum(rows, axis=0).tobytes()], pa.binary())})

    bundles = chosen.mapInArrow(bundle, "lang string, bundle binary")
    rows = bundles.groupBy("lang").applyInArrow(total, "lang string, bundle binary").collect()
    found = {r["lang"]: np.frombuffer(bytes(r["bundle"]), "<f8") for r in rows}
    return {k: v / np.linalg.norm(v) for k, v in sorted(found.items()) if v.any()}


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], keys: list[str], dimensions: int = DIMENSIONS) -> DataFrame:
    """``keys`` plus ``lang_pred, score`` of the column ``text``."""
    names = sorted(prototypes)
    table = np.stack([prototypes[k] for k in names]).astype(np.float32) if names else None
    sent = docs.sparkSession.sparkContext.broadcast((names, table))
    source = docs.select(F.struct(*[F.col(f"`{k}`") for k in keys]).alias("row"), F.col("text").cast("string").alias("text"))
    schema = source.select("row", F.lit("").alias("lang_pred"), F.lit(0.0).alias("score")).schema

    def run(batches):
        names, table = sent.value
        profiler = Profiler(dimensions)
        for part in slices(batches, "text"):
            n = part.num_rows
            langs, scores = np.full(n, "und", dtype=object), np.zeros(n)
            if names:
                rows = unit(profiler.vectors(texts(part)))
                cosines = rows @ table.T
                some = rows.any(axis=1)
                best = cosines.argmax(axis=1)
                langs[some] = np.array(names, dtype=object)[best[some]]
                scores[some] = np.clip(cosines[some, best[some]].astype(np.float64), 0.0, 1.0)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(langs.tolist(), pa.string()), pa.array(scores)], names=["row", "lang_pred", "score"]
            )

    return source.mapInArrow(run, schema).select("row.*", "lang_pred", "score")

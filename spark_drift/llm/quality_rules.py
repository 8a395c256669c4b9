"""Quality rules: fixed limits on document statistics, then gradient-boosted trees.

Statistics of a text are computed in one Arrow pass. Two limits are fixed: fewer
than 10 words, or more than a fifth of the words inside repeated 5-word windows, fail.
The rest is judged by boosted trees on the statistics, fitted on at most ``limit``
labelled documents and ``samples.SAMPLE_BYTES`` of their text (the ones with the smallest id
digests, each id once). Shares of symbols,
repeated lines and repeated words are constrained: more of them never raises a
document's score. The trees are flattened into numpy node arrays, broadcast, and
score a batch of documents level by level.

Edge cases: null text has no words and fails; a text without line breaks is one
line; without at least 20 labels of both kinds there are no trees and what passes the limits is
kept; repeated rows repeat; an empty table gives an empty result; other columns pass
through where rows are filtered.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.llm import boosting
from spark_drift.llm.batches import payloads, slices
from spark_drift.llm.samples import labelled

BLANKS = b" \t\n\x0b\x0c\r"
SYMBOLS = b"#*$%&|<>"
WINDOW = 5
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: column name -> direction in which it may move the score
FEATURES = {
    "log_words": 0,
    "mean_word": 0,
    "symbol_share": -1,
    "dup_line_share": -1,
    "repeat_share": -1,
    "distinct_share": 0,
    "digit_share": 0,
    "upper_share": 0,
    "mark_share": 0,
    "words_per_line": 0,
    "single_share": 0,
    "symbol_word_share": -1,
    "longest_word": 0,
    "common_share": 0,
}
DIGITS, UPPER, MARKS = b"0123456789", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b".,;:!?'\"()-/@_"


def statistics(text: bytes) -> tuple[tuple[int, ...], list[float]]:
    """The five counts and the model's features of one text."""
    words = text.split()
    n = len(words)
    bare = text.translate(None, BLANKS)
    chars = len(bare) if bare.isascii() else len(bare.decode("utf-8", "replace"))
    gone = lambda marks: len(bare) - len(bare.translate(None, marks))
    symbols = gone(SYMBOLS)
    lines = text.split(b"\n")
    filled = [x for x in lines if x.strip()]
    dup = len(filled) - len(set(filled))
    repeated = 0
    if n >= WINDOW:
        runs = list(zip(words, words[1:], words[2:], words[3:], words[4:], strict=False))
        if len(set(runs)) < len(runs):
            seen = Counter(runs)
            covered = bytearray(n)
            for k, run in enumerate(runs):
                if seen[run] > 1:
                    covered[k : k + WINDOW] = b"\x01" * WINDOW
            repeated = covered.count(1)
    counts = (n, chars, symbols, dup, repeated)
    if not n:
        return counts, [0.0] * len(FEATURES)
    kinds = Counter(words)
    size = max(chars, 1)
    odd = sum([c for w, c in kinds.items() if w.translate(None, SYMBOLS) != w]) if symbols else 0
    features = [
        float(np.log1p(n)),
        chars / n,
        symbols / size,
        dup / max(len(filled), 1),
        repeated / n,
        len(kinds) / n,
        gone(DIGITS) / size,
        gone(UPPER) / size,
        gone(MARKS) / size,
        n / max(len(filled), 1),
        sum([c for w, c in kinds.items() if len(w) == 1]) / n,
        odd / n,
        float(np.log1p(max(map(len, kinds)))),
        kinds.most_common(1)[0][1] / n,
    ]
    return counts, features


def base_failed(counts: np.ndarray) -> np.ndarray:
    n, repeated = counts[:, 0], counts[:, 4]
    return (n < 10) | (100 * repeated > 20 * n)


def fit_rules(docs: DataFrame, labels: DataFrame, limit: int = 12000) -> boosting.FlatTrees | None:
    """Trees for "label quality is 1", from at most ``limit`` labelled documents."""

    def run(batches):
        for part in slices(batches, "text"):
            rows = [statistics(x)[1] for x in payloads(part, "text")]
            yield pa.RecordBatch.from_arrays([part.column(1), pa.array(rows, pa.list_(pa.float64()))], names=["y", "x"])

    sample = labelled(docs, labels, "quality", limit).select(F.col("text").cast("binary").alias("text"), "y")
    rows = sample.mapInArrow(run, "y int, x array<double>").toArrow()
    y = rows.column("y").to_numpy().astype(np.float64)
    if min((y == 1).sum(), (y == 0).sum()) < 20:
        return None
    x = np.array(rows.column("x").to_pylist(), dtype=np.float64)
    order = np.lexsort([*x.T, y])  # rows arrive in any order; reruns agree
    return boosting.fit(x[order], y[order], np.array(list(FEATURES.values())))


VERDICT = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, score double"


def _verdicts(texts: list[bytes], trees: boosting.FlatTrees | None, threshold: float):
    found = [statistics(x) for x in texts]
    counts = np.array([c for c, _ in found], dtype=np.int64).reshape(-1, len(COUNTS))
    failed = base_failed(counts)
    score = trees.probability(np.array([f for _, f in found]).reshape(-1, len(FEATURES))) if trees else np.ones(len(texts))
    return counts, failed, ~failed & (score >= threshold), score


def judge(docs: DataFrame, trees: boosting.FlatTrees | None, threshold: float = 0.5) -> DataFrame:
    """``doc_id``, the counts, ``base_failed``, ``kept`` and the trees' ``score``."""
    sent = docs.sparkSession.sparkContext.broadcast(trees)

    def run(batches):
        for part in slices(batches, "text"):
            counts, failed, kept, score = _verdicts(payloads(part), sent.value, threshold)
            columns = [part.column(0), *map(pa.array, counts.T.copy()), pa.array(failed), pa.array(kept), pa.array(score)]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", *COUNTS, "base_failed", "kept", "score"])

    lean = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    return lean.mapInArrow(run, f"doc_id long, {VERDICT}")


def keep_good(docs: DataFrame, trees: boosting.FlatTrees | None, threshold: float = 0.5) -> DataFrame:
    """Rows of ``docs`` that pass, columns unchanged."""
    sent = docs.sparkSession.sparkContext.broadcast(trees)
    source = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("text").cast("binary").alias("text"))

    def run(batches):
        for part in slices(batches, "text"):
            kept = _verdicts(payloads(part), sent.value, threshold)[2]
            rows = part.column(0).filter(pa.array(kept))
            yield pa.RecordBatch.from_arrays([rows], names=["row"])

    return source.mapInArrow(run, source.select("row").schema).select("row.*")

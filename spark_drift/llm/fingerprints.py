"""Document fingerprints from content-defined chunks.

A gear hash, the sum of per-byte random numbers shifted by age, is computed for all
positions of a text at once by doubling: five shift-and-add steps cover a window of
32 bytes. A chunk may end where the top bits of the hash are zero; before the normal
size more bits are asked for than after it (normalised chunking), between a least
and a largest size. Boundaries depend on nearby bytes only, so an insertion changes
the chunks around it and no others.

A fingerprint is the set of chunk digests, each weighted by the bytes its chunk
covers. The containment of A in B is the weight of A's digests that B has too, as a
share of all A's weight; the empty text is contained in the empty text alone.

Neighbours. The next document in falling ``doc_id`` order is found with one exchange
of the texts: rows go to buckets between quantiles of the id, of which there are enough for
buckets of some thousand rows; an id that fills several quantiles is split by its texts' digests. Each
bucket also gets the head of the bucket that follows it as a ghost, one row whatever its
repeats, and a task walks its sorted buckets.

Edge cases: null text is empty; texts of any length are taken whole; a null
``doc_id`` comes last; equal ids are ordered by a digest of the text; repeated rows follow each other;
a table of one row is followed by itself; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.llm.batches import slices
from spark_drift.plans.lineage import shuffle_partitions

MIN, NORMAL, MAX = 16, 64, 256
#: boundary bits before and after the normal size (the mean between them fits NORMAL)
HARD, EASY = 8, 4
GEAR = np.random.Generator(np.random.PCG64(20240229)).integers(0, 1 << 32, 256, dtype=np.uint32)


def gear_hashes(data: np.ndarray) -> np.ndarray:
    """Gear hash at each byte, over the 32 bytes up to it."""
    h = GEAR[data]
    for k in (1, 2, 4, 8, 16):
        if len(h) <= k:
            break
        older = h[:-k] << np.uint32(k)
        h[k:] += older
    return h


def boundaries(data: bytes) -> list[int]:
    """Ends of the chunks of ``data``; the last is its length."""
    n = len(data)
    if n <= MIN:
        return [n] if n else []
    h = gear_hashes(np.frombuffer(data, dtype=np.uint8))
    easy = np.nonzero(h < np.uint32(1 << (32 - EASY)))[0]
    hard = (h[easy] < np.uint32(1 << (32 - HARD))).tolist()
    easy = (easy + 1).tolist()
    ends, start, k, count = [], 0, 0, len(easy)
    while n - start > MIN:
        low, middle, high = start + MIN, start + NORMAL, min(start + MAX, n)
        while k < count and easy[k] < low:
            k += 1
        end = high
        while k < count and easy[k] <= high:
            if easy[k] >= middle or hard[k]:
                end = easy[k]
                break
            k += 1
        ends.append(end)
        start = end
    if start < n:
        ends.append(n)
    return ends


def chunk_weights(text: str) -> dict[int, int]:
    """48-bit chunk digest -> bytes covered."""
    data = text.encode()
    out: dict[int, int] = {}
    start, digest = 0, xxhash.xxh3_64_intdigest
    for end in boundaries(data):
        d = digest(data[start:end]) >> 16
        out[d] = out.get(d, 0) + end - start
        start = end
    return out


def as_text(weights: dict[int, int]) -> str:
    return " ".join([f"{d:012x}{w:x}" for d, w in sorted(weights.items())])


def from_text(fingerprint: str) -> dict[int, int]:
    return {int(x[:12], 16): int(x[12:], 16) for x in fingerprint.split()}


def containment(a: dict[int, int], b: dict[int, int]) -> float:
    """Weight of ``a`` found in ``b``, 0 to 1."""
    if not a:
        return 0.0 if b else 1.0
    if a == b:
        return 1.0
    shared = a.keys() & b.keys()
    return sum([min(a[d], b[d]) for d in shared]) / sum(a.values()) if shared else 0.0


def fingerprint_documents(docs: DataFrame, keys: list[str]) -> DataFrame:
    """``keys`` plus ``fingerprint`` of the column ``text``."""
    source = docs.select(F.struct(*[F.col(f"`{k}`") for k in keys]).alias("row"), F.col("text").cast("string").alias("text"))

    def run(batches):
        for part in slices(batches, "text"):
            prints = [as_text(chunk_weights(x or "")) for x in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(prints, pa.string())], names=["row", "fingerprint"])

    schema = source.select("row", F.lit("").alias("fingerprint")).schema
    return source.mapInArrow(run, schema).select("row.*", "fingerprint")


def spliced(text: str, following: str) -> str:
    """``text`` with its last half replaced by as much of the start of ``following``."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


# --------------------------------------------------------------- neighbours

FIRST = -(1 << 63)
#: rows of a bucket, about, and the most buckets (their bounds travel with the plan)
BUCKET_ROWS, MOST_BUCKETS = 4096, 1 << 16
#: parts that one id may be split into
_PARTS = 1 << 20


def _numbers(values: list[int], kind: str) -> Column:
    """An array literal, folded when planned."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>") if values else F.lit([]).cast(f"array<{kind}>")


def _bucketed(keyed: DataFrame, found: list[int]) -> DataFrame:
    """``keyed`` with ``bucket``; ``found``: quantiles of the key, which repeat for a crowded one.

    Rows whose key is such a bound come after the other rows of its bucket and are split into
    as many parts, by ``tie``, as it has repeats."""
    bounds = sorted(set(found))
    times = Counter(found)
    at = place_in(_numbers(bounds, "long"), len(bounds), F.col("key"))
    repeats = F.get(_numbers([0, *[times[b] if times[b] > 1 else 0 for b in bounds]], "int"), F.col("at_"))
    own = F.coalesce(F.get(_numbers(bounds, "long"), F.col("at_") - 1) == F.col("key"), F.lit(False)) & (repeats > 0)
    part = F.when(own, 1 + F.least(F.floor(F.col("tie") / float(1 << 63) * repeats), repeats - 1)).otherwise(0)
    return keyed.withColumn("at_", at).withColumn("bucket", F.col("at_").cast("long") * _PARTS + part).drop("at_")


def place_in(bounds: Column, count: int, key: Column) -> Column:
    """How many of ``count`` sorted bounds lie at or below ``key``, by binary search."""
    if not count:
        return F.lit(0)
    steps = [1 << k for k in reversed(range(count.bit_length()))]
    fits = lambda at: (at <= count) & (F.get(bounds, at - 1) <= key)
    return F.aggregate(F.lit(steps), F.lit(0), lambda low, step: F.when(fits(low + step), low + step).otherwise(low))


def with_next(docs: DataFrame, buckets: int | None = None) -> DataFrame:
    """Rows ``bucket, key, ghost, doc_id, text``, dealt and sorted so that each row is
    followed by the next document of its bucket; a ghost closes each bucket."""
    parts = shuffle_partitions(docs.sparkSession)
    if buckets is None:
        buckets = min(MOST_BUCKETS, max(4 * parts, -(-docs.count() // BUCKET_ROWS)))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    ids = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST)).alias("key"))
    keyed = docs.select(
        F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST)).alias("key"),
        F.shiftrightunsigned(F.xxhash64(text), 1).alias("tie"),
        F.col("doc_id").cast("long").alias("doc_id"),
        text.alias("text"),
    )
    shares = [k / buckets for k in range(1, buckets)]
    found = ids.agg(F.percentile_approx("key", F.lit(shares), 10 * buckets)).first()[0] if shares else []
    dealt = _bucketed(keyed, list(found or []))
    # one row per bucket: its first row in the order of the walk, and the bucket it closes
    heads = dealt.groupBy("bucket").agg(F.min(F.struct(F.bitwise_not("key").alias("down"), "tie")).alias("head"))
    number = F.shiftright("bucket", 20)
    walk = Window.orderBy(number.desc(), F.col("bucket") % _PARTS)
    last = walk.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    closes = F.coalesce(F.lag("bucket").over(walk), F.last("bucket").over(last))
    heads = heads.select(F.bitwise_not("head.down").alias("head_key"), F.col("head.tie").alias("head_tie"), closes.alias("closes"))
    # at most two heads per quantile; of a head's repeats one row becomes the ghost
    same = (F.col("key") == F.col("head_key")) & (F.col("tie") == F.col("head_tie"))
    ghosts = dealt.join(F.broadcast(heads), same).groupBy(F.col("closes").alias("bucket"), "key", "tie").agg(F.first("text").alias("text"))
    rows = dealt.select("bucket", "key", F.lit(False).alias("ghost"), "doc_id", "text", "tie")
    ghosts = ghosts.select("bucket", "key", F.lit(True).alias("ghost"), F.lit(None).cast("long").alias("doc_id"), "text", "tie")
    return (
        rows.unionByName(ghosts)
        .repartition(max(parts, buckets // 4), "bucket")
        .sortWithinPartitions("bucket", "ghost", F.desc("key"), "tie")
        .drop("tie")
    )


NEIGHBOURS = (
    "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, "
    "near_edited double, near_next double"
)


def neighbour_likeness(docs: DataFrame) -> DataFrame:
    """For each document: its fingerprint, that of its edited text, and how much of it
    the edited text and the next document contain."""

    def run(batches):
        names = [x.split()[0] for x in NEIGHBOURS.split(", ")]
        pending, rows = None, []
        for part in slices(batches, "text", max_rows=512):
            columns = [part.column(k).to_pylist() for k in (0, 2, 3, 4)]
            for bucket, ghost, doc_id, text in zip(*columns, strict=True):
                same = pending is not None and pending[0] == bucket
                weights = chunk_weights(text) if not ghost or same else None
                if same:
                    _, own, own_text, own_weights = pending
                    edited = spliced(own_text, text)
                    edit_weights = own_weights if edited == own_text else chunk_weights(edited)
                    rows.append(
                        (
                            own,
                            len(own_text),
                            hashlib.sha256(edited.encode()).hexdigest(),
                            as_text(own_weights),
                            as_text(edit_weights),
                            containment(own_weights, edit_weights),
                            containment(own_weights, weights),
                        )
                    )
                pending = None if ghost else (bucket, doc_id, text, weights)
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], schema=_arrow(names))
                rows = []

    return with_next(docs).mapInArrow(run, NEIGHBOURS)


def _arrow(names: list[str]) -> pa.Schema:
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    return pa.schema(list(zip(names, kinds, strict=True)))

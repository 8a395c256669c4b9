"""SimHash near-duplicate groups found by bit-sliced comparison.

Plan. (1) One Arrow pass turns each text into a 64-bit fingerprint; only
``(doc_id, fingerprint)`` leaves it. (2) Distinct fingerprints are bucketed: the
64 bits are cut into ``radius + 2`` bands, and two fingerprints within the radius
agree on at least two whole bands, so each band pair is a bucket key and no link
can be missed. (3) In a bucket, fingerprints are stored as vertical bit planes;
distances of 64 lanes advance together in carry-save counters, and a block of
lanes is abandoned once each lane is past the radius. A bucket of more than 16
members passes on a spanning forest of its links, a smaller one its links, of which it has
120 at most. Buckets above ``chunk`` members are split into chunk pairs, so that a hot
bucket spreads over many tasks.
(4) Links are contracted to components by alternating star rounds, with a
checkpoint between rounds; neither links nor labels reach the driver.

Edge cases: null and blank texts have fingerprint zero and link like any other;
a text shorter than a shingle is one shingle; repeated rows keep their rows; a
null ``doc_id`` is never a component's name unless all its members are null; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.llm.batches import mix64, payloads, slices
from spark_drift.plans.lineage import cut, shuffle_partitions

SEED = 42
_ALL = np.uint64(0xFFFFFFFFFFFFFFFF)


def fingerprint(text: bytes, shingle_words: int = 3) -> int:
    """64-bit majority vote over the XXH64 values of all word shingles."""
    words = text.lower().split()
    n = len(words)
    if not n:
        return 0
    if n <= shingle_words:
        hashes = [xxhash.xxh64_intdigest(b" ".join(words), SEED)]
    else:
        digest, join = xxhash.xxh64_intdigest, b" ".join
        hashes = [digest(join(words[i : i + shingle_words]), SEED) for i in range(n - shingle_words + 1)]
    votes = np.zeros(64, dtype=np.int64)
    block = 1 << 14
    for start in range(0, len(hashes), block):
        h = np.array(hashes[start : start + block], dtype="<u8")
        votes += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(votes * 2 > len(hashes), bitorder="little")
    return int(bits.view("<u8")[0])


def fingerprints(docs: DataFrame, shingle_words: int = 3) -> DataFrame:
    """``(doc_id, text_hash, fp)`` per row; ``fp`` is the fingerprint as a signed long."""

    def run(batches):
        for part in slices(batches, "text"):
            fps = np.array([fingerprint(x, shingle_words) for x in payloads(part)], dtype=np.uint64)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), part.column(1), pa.array(fps.view(np.int64))], names=["doc_id", "text_hash", "fp"]
            )

    lean = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.xxhash64("text").alias("text_hash"),
        F.col("text").cast("binary").alias("text"),
    )
    return lean.mapInArrow(run, "doc_id long, text_hash long, fp long")


def bands(radius: int) -> list[tuple[int, int]]:
    """(shift, width) of ``radius + 2`` near-equal bands over 64 bits."""
    n = radius + 2
    edges = [round(64 * i / n) for i in range(n + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:], strict=False)]


# --------------------------------------------------------------- bit slicing


def planes_of(fps: np.ndarray) -> np.ndarray:
    """Vertical layout: row b holds bit b of every fingerprint, 64 lanes to a word."""
    lanes = -(-len(fps) // 64) * 64
    padded = np.zeros(lanes, dtype="<u8")
    padded[: len(fps)] = fps
    bits = np.unpackbits(padded.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.packbits(np.ascontiguousarray(bits.T), axis=1, bitorder="little").view("<u8")


class Counters:
    """Carry-save counters of all lanes; ``past`` marks lanes beyond the radius."""

    def __init__(self, shape, radius: int) -> None:
        # starting at top - radius makes the counter overflow exactly at radius + 1
        width = max(1, radius.bit_length())
        offset = (1 << width) - 1 - radius
        self.digits = [np.full(shape, _ALL if offset >> k & 1 else np.uint64(0)) for k in range(width)]
        self.past = np.zeros(shape, dtype=np.uint64)

    def add(self, plane: np.ndarray) -> None:
        carry = plane
        for k, digit in enumerate(self.digits):
            self.digits[k], carry = digit ^ carry, digit & carry
        self.past |= carry


def sliced_matches(queries: np.ndarray, planes: np.ndarray, radius: int, lanes: int) -> np.ndarray:
    """Boolean matrix: query i is within ``radius`` of lane j."""
    words = planes.shape[1]
    out = np.zeros((len(queries), words), dtype=np.uint64)
    for start in range(0, words, 64):
        block = planes[:, start : start + 64]
        count = Counters((len(queries), block.shape[1]), radius)
        for b in range(64):
            flip = np.where(queries >> np.uint64(b) & np.uint64(1), _ALL, np.uint64(0))
            count.add(block[b][None, :] ^ flip[:, None])
            if b % 8 == 7 and (count.past == _ALL).all():
                break
        out[:, start : start + 64] = ~count.past
    bits = np.unpackbits(out.view(np.uint8), axis=1, bitorder="little")
    return bits[:, :lanes].astype(bool)


def sliced_pairs(left: np.ndarray, right: np.ndarray, radius: int) -> np.ndarray:
    """For lanes that each hold one candidate pair: is it within ``radius``?"""
    out = np.zeros(len(left), dtype=bool)
    for start in range(0, len(left), 1 << 16):
        planes = planes_of(left[start : start + (1 << 16)] ^ right[start : start + (1 << 16)])
        count = Counters(planes.shape[1], radius)
        for b in range(64):
            count.add(planes[b])
            if b % 8 == 7 and (count.past == _ALL).all():
                break
        near = np.unpackbits((~count.past).view(np.uint8), bitorder="little")
        n = len(left[start : start + (1 << 16)])
        out[start : start + n] = near[:n].astype(bool)
    return out


def forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest member index of each node's component."""
    label = np.arange(n)
    while True:
        a, b = label[i], label[j]
        low = np.minimum(a, b)
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        while not np.array_equal(new[new], new):
            new = new[new]
        if np.array_equal(new, label):
            return label
        label = new


def links_within(fps: np.ndarray, side: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links of one bucket. ``side``: 0 and 1 are the two chunks of a split
    bucket, compared across only; 2 marks members compared with all."""
    n = len(fps)
    planes = planes_of(fps)
    found_i, found_j = [np.arange(0)], [np.arange(0)]
    label = np.arange(n)
    for start in range(0, n, 256):
        near = sliced_matches(fps[start : start + 256], planes, radius, n)
        i, j = np.nonzero(near)
        i += start
        keep = (i < j) & ((side[i] != side[j]) | (side[i] == 2))
        i, j = i[keep], j[keep]
        loose = label[i] != label[j]
        found_i.append(i[loose])
        found_j.append(j[loose])
        label = forest(n, np.concatenate([np.arange(n), i[loose]]), np.concatenate([label, j[loose]]))
    moved = np.nonzero(label != np.arange(n))[0]
    return fps[moved], fps[label[moved]]


def _bucket_links(batches, radius: int):
    """Rows of a partition come sorted by bucket; each bucket yields its spanning links."""

    def flush(keys, fps, sides):
        edges = np.nonzero(np.any(keys[1:] != keys[:-1], axis=1))[0] + 1
        starts = np.concatenate([[0], edges])
        sizes = np.diff(np.concatenate([starts, [len(fps)]]))
        left, right = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)]
        whole = np.add.reduceat((sides != 2).astype(np.int64), starts) == 0
        for g in np.unique(sizes[(sizes > 1) & (sizes <= 16) & whole]):
            rows = starts[(sizes == g) & whole][:, None] + np.arange(g)[None, :]
            for a, b in combinations(range(int(g)), 2):
                x, y = fps[rows[:, a]], fps[rows[:, b]]
                near = sliced_pairs(x, y, radius)
                left.append(x[near])
                right.append(y[near])
        for s, size in zip(starts, sizes, strict=True):
            if size > 16 or (size > 1 and sides[s : s + size].min() < 2):
                x, y = links_within(fps[s : s + size], sides[s : s + size], radius)
                left.append(x)
                right.append(y)
        x, y = np.concatenate(left), np.concatenate(right)
        return pa.RecordBatch.from_arrays([pa.array(x.view(np.int64)), pa.array(y.view(np.int64))], names=["a", "b"])

    held: list[np.ndarray] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in range(5)], axis=1)
        rows = np.concatenate([*held, rows])
        # the last bucket may go on in the next batch
        cut_at = len(rows) - int(np.argmin(np.all(rows[::-1, :3] == rows[-1, :3], axis=1)) or len(rows))
        done, held = rows[:cut_at], [rows[cut_at:]]
        if len(done):
            yield flush(done[:, :3], done[:, 4].view(np.uint64), done[:, 3])
    rows = np.concatenate(held) if held else np.zeros((0, 5), np.int64)
    if len(rows):
        yield flush(rows[:, :3], np.ascontiguousarray(rows[:, 4]).view(np.uint64), rows[:, 3])


def links(distinct: DataFrame, radius: int = 2, chunk: int = 2048) -> DataFrame:
    """Links ``(a, b)`` that connect all distinct ``fp`` values within ``radius``."""
    cuts = bands(radius)
    keys = []
    for no, ((s1, w1), (s2, w2)) in enumerate(combinations(cuts, 2)):
        first = F.shiftrightunsigned("fp", s1).bitwiseAND(F.lit((1 << w1) - 1))
        second = F.shiftrightunsigned("fp", s2).bitwiseAND(F.lit((1 << w2) - 1))
        # at most 48 bits of key, the number of the band pair above them
        keys.append(first + second * F.lit(1 << w1) + F.lit(no << 52))
    keyed = distinct.select("fp", F.explode(F.array(*keys)).alias("bucket"))
    sizes = keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > 1)
    crowded = keyed.join(sizes, "bucket")
    parts = F.ceil(F.col("n") / F.lit(chunk)).cast("long")
    mine = F.pmod(F.xxhash64("fp"), parts)
    others = F.transform(
        F.sequence(F.lit(0).cast("long"), parts - 1),
        lambda x: F.struct(
            F.least(mine, x).alias("p"),
            F.greatest(mine, x).alias("q"),
            F.when(mine == x, F.lit(2)).when(mine < x, F.lit(0)).otherwise(F.lit(1)).cast("long").alias("side"),
        ),
    )
    dealt = crowded.select("bucket", "fp", F.explode(others).alias("o")).select(
        "bucket", F.col("o.p").alias("p"), F.col("o.q").alias("q"), F.col("o.side").alias("side"), "fp"
    )
    return (
        dealt.repartition("bucket", "p", "q")
        .sortWithinPartitions("bucket", "p", "q", "side", "fp")
        .mapInArrow(lambda it: _bucket_links(it, radius), "a long, b long")
    )


# --------------------------------------------------------------- components


def components(pairs: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for every node of ``pairs (a, b)``; root is the smallest member.

    A round rewires each node to the smallest neighbour, first its larger
    neighbours and then itself; paths halve, so rounds grow with the logarithm of
    the longest path. Minima are partial aggregates joined back: a hub is a
    skewed join side that adaptive execution may split.
    """
    edges = cut(pairs.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = None
    for _ in range(max_rounds):
        both = edges.union(edges.select("v", "u")).toDF("u", "v")
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        stars = F.array(
            F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v"))
        )
        edges = cut(large.join(low, "u").select(F.inline(stars)).where("u <> v").distinct())
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == state:
            break
        state = tuple(now)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots)


def near_duplicates(docs: DataFrame, shingle_words: int = 3, radius: int = 2, chunk: int = 2048) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, text_hash, fp, root, component_id``.

    ``component_id`` is the smallest ``doc_id`` whose fingerprint can be reached by
    links of ``radius`` or fewer differing bits.
    """
    marked = cut(fingerprints(docs, shingle_words))
    nodes = marked.groupBy("fp").agg(F.min("doc_id").alias("low"))
    linked = components(links(nodes.select("fp"), radius, chunk)).withColumnRenamed("node", "fp")
    rooted = nodes.join(linked, "fp", "left").select("fp", "low", F.coalesce("root", "fp").alias("root"))
    rooted = cut(rooted)
    names = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    return marked.join(rooted.join(names, "root").select("fp", "root", "component_id"), "fp")


# ------------------------------------------------------------ exact similarity


def shingle_set(text: bytes, shingle_words: int = 5) -> np.ndarray:
    """Sorted distinct XXH64 values of all word shingles; a shorter text is one shingle."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    last = max(1, len(words) - shingle_words + 1)
    return np.unique(np.array([xxhash.xxh64_intdigest(b" ".join(words[i : i + shingle_words]), SEED) for i in range(last)], np.uint64))


def vote_bits(hashes: np.ndarray) -> int:
    """64-bit majority vote over distinct shingle values."""
    if not len(hashes):
        return 0
    votes = np.zeros(64, np.int64)
    for start in range(0, len(hashes), 1 << 14):
        part = hashes[start : start + (1 << 14)].astype("<u8")
        votes += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(votes * 2 > len(hashes), bitorder="little").view("<u8")[0])


def print_set(hashes: np.ndarray) -> list[int]:
    """Four fingerprints of one set, by independent hashes."""
    out = [vote_bits(hashes)]
    for _ in range(3):
        hashes = mix64(hashes + np.uint64(1))
        out.append(vote_bits(hashes))
    return out


def least_common(n: int, similarity: float) -> int:
    """Shingles that a set of ``n`` shares at least with any set of that Jaccard similarity."""
    return math.ceil(similarity * n - 1e-9)


#: bands of a sketch and minima of a band: two sets of similarity 0.8 agree in no band with
#: probability (1 - 0.8**3)**26, some 8 in a thousand million
BANDS, IN_BAND = 26, 3
#: rows of three numbers up to which a table is broadcast; larger ones are shuffled
BROADCAST_ROWS = 1 << 20
#: sets up to this size meet by their smallest values, which misses nothing
SMALL_SET = 40
_ODD = np.random.Generator(np.random.PCG64(20240611)).integers(0, 1 << 63, (2, BANDS * IN_BAND), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def sketch(hashes: np.ndarray) -> np.ndarray:
    """One key per band: its number and the least values of the set under the band's own orders."""
    low = np.full(BANDS * IN_BAND, _ALL)
    for start in range(0, len(hashes), 4096):
        part = hashes[start : start + 4096][None, :] * _ODD[0][:, None] + _ODD[1][:, None]
        part ^= part >> np.uint64(29)
        low = np.minimum(low, (part * np.uint64(0x9E3779B97F4A7C15)).min(axis=1))
    low = low.reshape(BANDS, IN_BAND)
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for k in range(IN_BAND):
        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) ^ low[:, k])
    return key


def meeting_keys(hashes: np.ndarray, similarity: float) -> np.ndarray:
    """Keys of which two sets of that similarity share one: small sets a sufficient number of their
    smallest values, others those of their sketch. Sets near the border have both, as two sets of that
    similarity may lie on either side of it."""
    n, keys = len(hashes), []
    if n <= SMALL_SET:
        keys.append(hashes[: n - least_common(n, similarity) + 1])
    if n >= similarity * SMALL_SET:
        keys.append(sketch(hashes))
    return np.concatenate(keys)


def marked_sets(docs: DataFrame, similarity: float = 0.8, shingle_words: int = 5) -> DataFrame:
    """``(doc_id, text_hash, node, fp, keys, short_fp)`` per row. ``short_fp`` is the query's
    fingerprint of three words, the others are of the shingle set: ``node`` names the shingle set; two
    sets of that similarity share one of their ``keys`` at least."""

    def run(batches):
        for part in slices(batches, "text"):
            nodes, fps, keys, short = [], [], [], []
            for x in payloads(part):
                s = shingle_set(x, shingle_words)
                nodes.append(xxhash.xxh64_intdigest(s.tobytes(), SEED))
                fps.append(np.array(print_set(s), np.uint64).view(np.int64))
                short.append(fingerprint(x))
                keys.append(meeting_keys(s, similarity).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [
                    part.column(0), part.column(1), pa.array(np.array(nodes, np.uint64).view(np.int64)),
                    pa.array(fps, pa.list_(pa.int64())), pa.array(keys, pa.list_(pa.int64())),
                    pa.array(np.array(short, np.uint64).view(np.int64)),
                ],
                names=["doc_id", "text_hash", "node", "fp", "keys", "short_fp"],
            )

    lean = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"), F.col("text").cast("binary").alias("text")
    )
    return lean.mapInArrow(run, "doc_id long, text_hash long, node long, fp array<long>, keys array<long>, short_fp long")


def _dealt(members: DataFrame, key: str, chunk: int) -> DataFrame:
    """Members of the groups of two or more, those of large groups once per pair of chunks ``p, q``."""
    sizes = members.groupBy(key).agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    parts = F.ceil(F.col("n") / F.lit(chunk)).cast("long")
    mine = F.pmod(F.xxhash64("node"), parts)
    each = F.transform(
        F.sequence(F.lit(0).cast("long"), parts - 1), lambda x: F.struct(F.least(mine, x).alias("p"), F.greatest(mine, x).alias("q"))
    )
    return members.join(sizes, key).select(*members.columns, F.inline(each))


def _all_near(fps: np.ndarray, i: np.ndarray, j: np.ndarray, radius: int) -> np.ndarray:
    """For pairs of rows: does each of their fingerprints differ in ``radius`` bits at most?"""
    ok = np.ones(len(i), bool)
    for k in range(fps.shape[1]):
        rest = np.nonzero(ok)[0]
        ok[rest] = sliced_pairs(fps[i[rest], k], fps[j[rest], k], radius)
    return ok


def _near_groups(batches, radius: int):
    """Of each bucket the members that ``radius`` links, as groups named by their smallest member."""

    def flush(rows):
        edges = np.nonzero(np.any(rows[1:, :3] != rows[:-1, :3], axis=1))[0] + 1
        starts = np.concatenate([[0], edges])
        sizes = np.diff(np.concatenate([starts, [len(rows)]]))
        nodes, fps = rows[:, 3], np.ascontiguousarray(rows[:, 4:]).view(np.uint64)
        found: dict[tuple, None] = {}
        twos = starts[sizes == 2]
        for s in twos[_all_near(fps, twos, twos + 1, radius)]:
            found[tuple(sorted(nodes[s : s + 2].tolist()))] = None
        for s, size in zip(starts[sizes > 2], sizes[sizes > 2], strict=True):
            own = fps[s : s + size]
            planes, label = planes_of(own[:, 0]), np.arange(size)
            for at in range(0, size, 256):
                i, j = np.nonzero(sliced_matches(own[at : at + 256, 0], planes, radius, int(size)))
                i, j = i[i + at < j] + at, j[i + at < j]
                near = _all_near(own, i, j, radius)
                label = forest(int(size), np.concatenate([np.arange(size), i[near]]), np.concatenate([label, j[near]]))
            order = np.argsort(label, kind="stable")
            for group in np.split(order, np.nonzero(np.diff(label[order]))[0] + 1):
                if len(group) > 1:
                    found[tuple(sorted(nodes[s : s + size][group].tolist()))] = None
        # a group is named by its smallest member, so that the much alike groups of a crowd's many buckets become one
        many = np.array([len(g) for g in found], np.int64)
        names = np.repeat(np.array([g[0] for g in found], np.int64), many)
        return pa.RecordBatch.from_arrays([pa.array(names), pa.array(np.array([x for g in found for x in g], np.int64))], names=["grp", "node"])

    held = np.zeros((0, 8), np.int64)
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = np.concatenate([held, np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in range(8)], axis=1)])
        # the last bucket may go on in the next batch
        other = np.nonzero(np.any(rows[:, :3] != rows[-1, :3], axis=1))[0]
        end = int(other[-1]) + 1 if len(other) else 0
        done, held = rows[:end], rows[end:]
        if len(done):
            yield flush(done)
    if len(held):
        yield flush(held)


def similar_links(nodes: np.ndarray, sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Links that connect all members whose sets are similar enough; pairs that are
    connected already are not compared again."""
    label, sizes = np.arange(len(nodes)), np.array([len(s) for s in sets])
    out = []
    for i in range(len(nodes) - 1):
        rest = np.nonzero(label[i + 1 :] != label[i])[0] + i + 1
        low, high = np.minimum(sizes[i], sizes[rest]), np.maximum(sizes[i], sizes[rest])
        for j in rest[low >= similarity * high - 1e-9]:
            if label[i] == label[j]:
                continue
            common = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if common >= similarity * (sizes[i] + sizes[j] - common) - 1e-9:
                out.append((int(nodes[i]), int(nodes[j])))
                label[label == label[j]] = label[i]
    return out


def similar_groups(
    docs: DataFrame, near: int = 4, similarity: float = 0.8, shingle_words: int = 5, radius: int = 24, chunk: int = 2048, few: int = 1024
) -> DataFrame:
    """``doc_id, text_hash, root`` per row: rows of one root are connected by pairs whose
    shingle sets have that Jaccard similarity or more, or whose three-word fingerprints
    differ in ``near`` bits at most.

    Sets that share one of their keys meet in a bucket, which misses a pair of large sets with a probability
    below 10**-8 and of small ones none; there the bit-sliced comparison drops those of whose four
    fingerprints one is beyond ``radius``, and the sets decide on the rest.
    """
    marked = cut(marked_sets(docs, similarity, shingle_words))
    named = F.struct(F.coalesce("doc_id", "text_hash").alias("id"), "text_hash")
    nodes = cut(marked.groupBy("node").agg(F.min(named).alias("one"), F.first("fp").alias("fp"), F.first("keys").alias("keys")))
    met = _dealt(nodes.select(F.explode("keys").alias("bucket"), "node"), "bucket", chunk)
    prints = [F.col("fp")[k].alias(f"f{k}") for k in range(4)]
    met = met.select("bucket", "p", "q", "node").join(nodes.select("node", *prints), "node").select("bucket", "p", "q", "node", "f0", "f1", "f2", "f3")
    # small rows that cost much: a stated number of tasks, which is not lowered by their bytes
    spark = docs.sparkSession
    tasks = max(shuffle_partitions(spark), 2 * spark.sparkContext.defaultParallelism)
    met = met.repartition(tasks, "bucket", "p", "q").sortWithinPartitions("bucket", "p", "q", "node")
    groups = cut(met.mapInArrow(lambda it: _near_groups(it, radius), "grp long, node long").distinct())
    wanted = cut(nodes.select("node", "one.id", "one.text_hash").join(groups.select("node").distinct(), "node"))
    if wanted.count() <= BROADCAST_ROWS:
        wanted = F.broadcast(wanted)
    texts = docs.select(F.xxhash64("text").alias("text_hash"), F.col("doc_id").cast("long").alias("id"), F.col("text").cast("binary").alias("text"))
    texts = texts.withColumn("id", F.coalesce("id", "text_hash")).join(wanted, ["id", "text_hash"]).dropDuplicates(["node"]).select("node", "text")

    def packed(batches):
        for part in slices(batches, "text"):
            sets = [shingle_set(x, shingle_words).tobytes() for x in payloads(part)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.binary())], names=["node", "items"])

    def exact(table: pa.Table) -> pa.Table:
        names = table.column("node").to_numpy()
        sets = [np.frombuffer(x, np.uint64) for x in table.column("items").to_pylist()]
        found = np.array(similar_links(names, sets, similarity), np.int64).reshape(-1, 2)
        return pa.table({"a": found[:, 0], "b": found[:, 1]})

    sets = texts.mapInArrow(packed, "node long, items binary")
    pairs = _dealt(groups, "grp", few).join(sets, "node").groupBy("grp", "p", "q").applyInArrow(exact, "a long, b long")
    prints = marked.select("node", F.col("short_fp").alias("fp")).distinct()
    reps = cut(prints.groupBy("fp").agg(F.min("node").alias("b")))
    same = prints.join(reps, "fp").where("node <> b").select(F.col("node").alias("a"), "b")
    ends = [reps.toDF(c, f"{c}_node") for c in "ab"]
    close = links(reps.select("fp"), near, chunk).join(ends[0], "a").join(ends[1], "b").select(F.col("a_node").alias("a"), F.col("b_node").alias("b"))
    roots = components(pairs.union(same).union(close))
    return marked.select("doc_id", "text_hash", "node").join(roots, "node", "left").select("doc_id", "text_hash", F.coalesce("root", "node").alias("root"))


def keep_similar_one(docs: DataFrame, near: int = 4, similarity: float = 0.8, shingle_words: int = 5) -> DataFrame:
    """``docs`` with one row left of each group of ``similar_groups``."""
    return _keep_first(docs, similar_groups(docs, near, similarity, shingle_words))


def keep_one(docs: DataFrame, shingle_words: int = 3, radius: int = 2) -> DataFrame:
    """``docs`` with one row left of each group of near copies, columns unchanged.

    The row with the smallest ``doc_id`` stays; among equal ids the smallest text
    hash; among repeated rows one. Rows without an id cannot be named in a group
    and all stay.
    """
    return _keep_first(docs, near_duplicates(docs, shingle_words, radius))


def _keep_first(docs: DataFrame, found: DataFrame) -> DataFrame:
    best = F.min(F.struct("doc_id", "text_hash")).alias("best")
    winners = found.where("doc_id is not null").groupBy("root").agg(best).select("best.doc_id", "best.text_hash")
    names = docs.columns
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row")).select(
        "row", F.col("row.doc_id").cast("long").alias("doc_id"), F.xxhash64("row.text").alias("text_hash")
    )
    copy = F.row_number().over(Window.partitionBy("doc_id", "text_hash").orderBy(F.lit(1)))
    kept = packed.join(winners, ["doc_id", "text_hash"]).withColumn("copy", copy).where("copy = 1").select("row")
    return kept.union(packed.where("doc_id is null").select("row")).select("row.*")

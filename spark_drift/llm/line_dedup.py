"""Removing lines that many documents share, by a sharded minimal perfect hash.

Plan. (1) Each document's distinct line keys are hashed inside the JVM; the distinct
documents of each hash are counted, first by hash and document, then by hash, so one
very common line spreads over all tasks. (2) All distinct line hashes are dealt to
shards; each shard builds, in its own task, a minimal perfect hash (levels of bit
arrays, the index of a key being the rank of its bit) and two compact arrays at these
indexes: a fingerprint of the hash and its document count. (3) Documents probe the
arrays, and the count found there decides about each line; no line is joined.

An index of at most ``index_bytes`` is shipped whole to the probing tasks, a broadcast of
checked size, and documents are scanned once more. A larger one stays where it is: each
batch of documents sends its hashes, packed, to their shards, these answer with the
common ones, and a document meets its answers by a digest of its text. Shards and texts
that hold more than a thousandth of all such traffic are split.

A line key is the line without blanks at both ends, A-Z in lower case. 64-bit line
hashes stand for keys. Every line of the indexed table is in the index; a line of
another table passes for a member with probability 2**-32, as the arrays keep 32 bits.

Documents are told apart by ``doc_id``: rows of one id are one document, and a line counts
once for it. Edge cases: a row without an id is a document of its own (equal texts
without an id count once); a null or empty text is one empty line and stays; a text of which
all lines go becomes the empty text and its row stays; repeated rows stay; an empty
table gives an empty result; other columns, whatever their names, pass through untouched.
"""

from __future__ import annotations

import io
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spark_drift.llm.batches import mix64, payloads, slices
from spark_drift.plans.lineage import cut

SEED = 42
BLANKS = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: characters that ``kept_lines`` returns besides the columns of its input
ADDED = ("kept_text", "n_lines", "n_dropped")


def line_counts(docs: DataFrame, min_chars: int = 1, per: str = "doc_id") -> DataFrame:
    """``(hash, docs)`` of all distinct line keys: how many documents contain each, documents
    being told apart by id or, ``per="text"``, by text, so that exact copies count once."""
    lines = F.split(F.translate("text", _UPPER, _LOWER), "\n")
    keys = F.transform(lines, lambda x: F.btrim(x, F.lit(BLANKS)))
    keys = F.filter(keys, lambda k: F.char_length(k) >= min_chars)
    hashes = F.array_distinct(F.transform(keys, lambda k: F.xxhash64(k)))
    # a row without an id is told from ids by the second number
    by_text = F.lit(True) if per == "text" else F.col("doc_id").isNull()
    named = F.when(by_text, F.xxhash64("text")).otherwise(F.col("doc_id").cast("long")).alias("of")
    each = docs.select(named, by_text.alias("nameless"), F.explode(hashes).alias("hash"))
    return each.groupBy("hash").agg(F.count_distinct("of", "nameless").alias("docs"))


# ------------------------------------------------------ minimal perfect hash


class PerfectShard:
    """Minimal perfect hash of distinct 64-bit keys with fingerprints and counts."""

    def __init__(self, words, spans, rest, prints, counts) -> None:
        self.words, self.spans, self.rest = words, spans, rest
        self.prints, self.counts = prints, counts
        ones = np.bitwise_count(words).astype(np.int64)
        self.rank = np.concatenate([[0], np.cumsum(ones)])

    @staticmethod
    def _place(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        salt = np.uint64((level + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        return (mix64(keys ^ salt) % np.uint64(size)).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray, counts: np.ndarray, gamma: float = 2.0, levels: int = 40) -> PerfectShard:
        left, words, spans = keys, [], []
        for level in range(levels):
            if not len(left):
                break
            size = max(64, -(-int(gamma * len(left)) // 64) * 64)
            at = cls._place(left, level, size)
            alone = np.bincount(at, minlength=size) == 1
            words.append(np.packbits(alone, bitorder="little").view("<u8"))
            spans.append(size)
            left = left[~alone[at]]
        shard = cls(
            np.concatenate(words) if words else np.zeros(0, "<u8"),
            np.array(spans, dtype=np.int64),
            np.sort(left),
            np.zeros(len(keys), np.uint32),
            np.zeros(len(keys), np.uint32),
        )
        at = shard.index(keys)
        shard.prints[at] = keys.astype(np.uint32)
        shard.counts[at] = np.minimum(counts, (1 << 32) - 1)
        return shard

    def index(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key; -1 where no level has its bit. A stranger may get a slot."""
        out = np.full(len(keys), -1, dtype=np.int64)
        open_ = np.arange(len(keys))
        base = 0
        for level, size in enumerate(self.spans):
            if not len(open_):
                return out
            at = self._place(keys[open_], level, int(size)) + base
            word, bit = at >> 6, (at & 63).astype(np.uint64)
            hit = (self.words[word] >> bit & np.uint64(1)).astype(bool)
            below = np.bitwise_count(self.words[word[hit]] & ((np.uint64(1) << bit[hit]) - np.uint64(1)))
            out[open_[hit]] = self.rank[word[hit]] + below
            open_ = open_[~hit]
            base += int(size)
        if len(self.rest) and len(open_):
            at = np.minimum(np.searchsorted(self.rest, keys[open_]), len(self.rest) - 1)
            hit = self.rest[at] == keys[open_]
            out[open_[hit]] = self.rank[-1] + at[hit]
        return out

    def lookup(self, keys: np.ndarray) -> np.ndarray:
        """Document count of each key, 0 for strangers."""
        if not len(self.counts):
            return np.zeros(len(keys), np.int64)
        at = self.index(keys)
        same = (at >= 0) & (self.prints[np.maximum(at, 0)] == keys.astype(np.uint32))
        return np.where(same, self.counts[np.maximum(at, 0)], 0).astype(np.int64)

    def dump(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, words=self.words, spans=self.spans, rest=self.rest, prints=self.prints, counts=self.counts)
        return out.getvalue()

    @classmethod
    def load(cls, blob: bytes) -> PerfectShard:
        with np.load(io.BytesIO(blob)) as z:
            return cls(z["words"], z["spans"], z["rest"], z["prints"], z["counts"])


def shard_of(hashes: np.ndarray, shards: int) -> np.ndarray:
    return ((hashes >> np.uint64(33)) % np.uint64(shards)).astype(np.int64)


def build_index(counts: DataFrame, shard_keys: int = 1 << 17) -> DataFrame:
    """``(shard, shards, n, blob)``: one perfect hash per shard, built on the executors."""
    counts = cut(counts)
    shards = max(1, -(-counts.count() // shard_keys))
    dealt = counts.withColumn("shard", F.shiftrightunsigned("hash", 33) % F.lit(shards))

    def build(key, rows):
        hashes = rows["hash"].to_numpy(np.int64).view(np.uint64)
        shard = PerfectShard.build(hashes, rows["docs"].to_numpy(np.int64))
        return pd.DataFrame({"shard": [key[0]], "shards": [shards], "n": [len(rows)], "blob": [shard.dump()]})

    schema = "shard long, shards long, n long, blob binary"
    return cut(dealt.groupBy("shard").applyInPandas(build, schema))


def kept_lines(
    docs: DataFrame, min_docs: int = 10, min_chars: int = 1, index_bytes: int = 64 << 20, shard_keys: int = 1 << 17, per: str = "doc_id"
) -> DataFrame:
    """Columns of ``docs`` (as struct ``row``) plus ``kept_text, n_lines, n_dropped`` (as struct ``added``)."""
    index = build_index(line_counts(docs, min_chars, per), shard_keys)
    size = index.agg(F.coalesce(F.sum(F.length("blob")), F.lit(0)), F.coalesce(F.max("shards"), F.lit(1))).first()
    if size[0] <= index_bytes:
        return _probe_here(docs, index, size[1], min_docs, min_chars)
    return _probe_there(docs, index, size[1], min_docs, min_chars)


def _hashed(payload: list[bytes], min_chars: int) -> tuple[list[list[bytes]], np.ndarray, np.ndarray, np.ndarray]:
    """Lines of each text, their hashes, which of them have a key long enough, and where texts begin."""
    split = [x.split(b"\n") for x in payload]
    keys = [line.strip().lower() for lines in split for line in lines]
    hashes = np.array([xxhash.xxh64_intdigest(k, SEED) for k in keys], dtype=np.uint64)
    if min_chars > 1:
        full = np.array([len(k.decode("utf-8", "replace")) >= min_chars for k in keys], dtype=bool)
    else:
        full = np.array([len(k) >= min_chars for k in keys], dtype=bool)
    return split, hashes, full, np.cumsum([0, *map(len, split)])


def _answers(tables: dict[int, PerfectShard], shards: int, hashes: np.ndarray) -> np.ndarray:
    """Document counts of hashes, each read from its own shard."""
    counts = np.zeros(len(hashes), np.int64)
    where = shard_of(hashes, shards)
    order = np.argsort(where, kind="stable")
    edges = np.nonzero(np.diff(where[order]))[0] + 1
    for mine in np.split(order, edges):
        if len(mine) and int(where[mine[0]]) in tables:
            counts[mine] = tables[int(where[mine[0]])].lookup(hashes[mine])
    return counts


def _without(row: pa.Array, split: list[list[bytes]], drop: np.ndarray, bounds: np.ndarray) -> pa.RecordBatch:
    """The batch that goes out: rows with their texts less the dropped lines."""
    kept, gone = [], []
    for k, lines in enumerate(split):
        mask = drop[bounds[k] : bounds[k + 1]]
        gone.append(int(mask.sum()))
        kept.append(b"\n".join([x for x, d in zip(lines, mask, strict=True) if not d] if gone[-1] else lines))
    columns = [pa.array(kept, pa.binary()).cast(pa.string()), pa.array([len(x) for x in split], pa.int64()), pa.array(gone, pa.int64())]
    return pa.RecordBatch.from_arrays([row, pa.StructArray.from_arrays(columns, names=list(ADDED))], names=["row", "added"])


def _packed(docs: DataFrame) -> DataFrame:
    """``row, text``: all columns in a struct, and the text's bytes."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("text").cast("binary").alias("text"))


def _out_schema(source: DataFrame) -> T.StructType:
    tail = T._parse_datatype_string("added struct<kept_text:string,n_lines:bigint,n_dropped:bigint>")
    return T.StructType([source.schema["row"], *tail.fields])


_LOADED: dict[str, dict[int, PerfectShard]] = {}


def _probe_here(docs: DataFrame, index: DataFrame, shards: int, min_docs: int, min_chars: int) -> DataFrame:
    """The whole index in each probing task."""
    blobs = {r["shard"]: bytes(r["blob"]) for r in index.select("shard", "blob").collect()}
    sent = docs.sparkSession.sparkContext.broadcast(blobs)
    token = uuid.uuid4().hex
    source = _packed(docs)

    def run(batches):
        if token not in _LOADED:  # once per Python worker
            _LOADED.clear()
            _LOADED[token] = {k: PerfectShard.load(v) for k, v in sent.value.items()}
        for part in slices(batches, "text"):
            split, hashes, full, bounds = _hashed(payloads(part), min_chars)
            drop = full & (_answers(_LOADED[token], shards, hashes) >= min_docs)
            yield _without(part.column(0), split, drop, bounds)

    return source.mapInArrow(run, _out_schema(source))


def _hot(rows: DataFrame, keys: list[str], amount: Column, share: int = 1000) -> DataFrame:
    """``keys.., ways``: the keys with more than a thousandth of everything, hence fewer than
    ``share`` of them, and into how many parts each is split."""
    by = rows.groupBy(*keys).agg(F.sum(amount).alias("n"))
    total = by.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    fair = max(1, total // share)
    return by.where(F.col("n") > fair).select(*keys, F.ceil(F.col("n") / F.lit(fair)).cast("int").alias("ways"))


def _probe_there(docs: DataFrame, index: DataFrame, shards: int, min_docs: int, min_chars: int) -> DataFrame:
    """Hashes travel to the shards, answers to the documents."""
    named = [F.xxhash64("text").alias("k1"), F.xxhash64("text", F.lit("second")).alias("k2")]
    lean = docs.select(*named, F.col("text").cast("binary").alias("text"))

    def ask(batches):
        for part in slices(batches, "text"):
            names = np.stack([part.column(k).to_numpy(zero_copy_only=False) for k in (0, 1)], axis=1)
            first = np.unique(names, axis=0, return_index=True)[1]  # copies in a batch ask once
            values = payloads(part)
            _, hashes, full, bounds = _hashed([values[k] for k in first], min_chars)
            of = np.repeat(np.arange(len(first)), np.diff(bounds))[full]
            asked = np.unique(np.stack([hashes[full], of.astype(np.uint64)], axis=1), axis=0)
            where = shard_of(asked[:, 0], shards)
            order = np.argsort(where, kind="stable")
            for mine in np.split(order, np.nonzero(np.diff(where[order]))[0] + 1):
                if not len(mine):
                    continue
                who = names[first][asked[mine, 1].astype(np.int64)]
                message = np.stack([asked[mine, 0].view(np.int64), who[:, 0], who[:, 1]], axis=1)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([int(where[mine[0]])]), pa.array([message.astype("<i8").tobytes()], pa.binary())], names=["shard", "blob"]
                )

    asked = cut(lean.mapInArrow(ask, "shard long, blob binary"))
    hot = _hot(asked, ["shard"], F.length("blob"))
    ways = F.coalesce("ways", F.lit(1))
    tables = index.join(F.broadcast(hot), "shard", "left").select(
        "shard", F.explode(F.sequence(F.lit(0), ways - 1)).alias("way"), F.lit(0).alias("kind"), "blob"
    )
    asked = asked.join(F.broadcast(hot), "shard", "left").select("shard", F.pmod(F.xxhash64("blob"), ways).cast("int").alias("way"), F.lit(1).alias("kind"), "blob")

    def answer(batches):
        table, of = None, None
        for part in slices(batches, "blob"):
            shard, way, kind = (part.column(k).to_pylist() for k in (0, 1, 2))
            found = []
            for s, w, k, blob in zip(shard, way, kind, part.column(3).to_pylist(), strict=True):
                if k == 0:  # a shard's arrays come before its questions
                    table, of = PerfectShard.load(blob), (s, w)
                    continue
                message = np.frombuffer(blob, "<i8").reshape(-1, 3)
                common = table.lookup(message[:, 0].view(np.uint64)) >= min_docs if of == (s, w) else np.zeros(len(message), bool)
                found.append(message[common])
            rows = np.concatenate(found) if found else np.zeros((0, 3), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(rows[:, k])) for k in (1, 2, 0)], names=["k1", "k2", "hash"])

    both = tables.unionByName(asked).repartition("shard", "way").sortWithinPartitions("shard", "way", "kind")
    gone = both.mapInArrow(answer, "k1 long, k2 long, hash long").groupBy("k1", "k2").agg(F.collect_set("hash").alias("gone"))
    crowd = _hot(docs.select(*named), ["k1", "k2"], F.lit(1)).withColumnsRenamed({"k1": "h1", "k2": "h2"})
    same = (F.col("k1") == F.col("h1")) & (F.col("k2") == F.col("h2"))
    source = _packed(docs).select("row", F.xxhash64("row.text").alias("k1"), F.xxhash64("row.text", F.lit("second")).alias("k2"))
    part_of = F.pmod(F.xxhash64("row.doc_id"), ways).cast("int")
    source = source.join(F.broadcast(crowd), same, "left").select("row", "k1", "k2", part_of.alias("way"))
    gone = gone.join(F.broadcast(crowd), same, "left").select("k1", "k2", F.explode(F.sequence(F.lit(0), ways - 1)).alias("way"), "gone")
    # the text is taken out of the row behind the exchange, which then moves it once
    met = source.join(gone, ["k1", "k2", "way"], "left").select("row", F.col("row.text").cast("binary").alias("text"), "gone")

    def run(batches):
        for part in slices(batches, "text"):
            split, hashes, full, bounds = _hashed(payloads(part), min_chars)
            drop = np.zeros(len(hashes), bool)
            for k, found in enumerate(part.column(2).to_pylist()):
                if found:
                    mine = slice(bounds[k], bounds[k + 1])
                    drop[mine] = full[mine] & np.isin(hashes[mine].view(np.int64), np.array(found, np.int64))
            yield _without(part.column(0), split, drop, bounds)

    return met.mapInArrow(run, _out_schema(met))


def drop_common_lines(docs: DataFrame, min_docs: int = 10, min_chars: int = 1, per: str = "doc_id") -> DataFrame:
    """``docs`` with the common lines taken out of ``text``; ``n_chars``, where the
    table has it, is the new length in code points. Columns and rows stay."""
    kept = kept_lines(docs, min_docs, min_chars, per=per)
    out = []
    for c in docs.columns:
        old = F.col(f"row.`{c}`")
        if c == "text":
            old = F.col("added.kept_text")
        elif c == "n_chars":
            old = F.char_length("added.kept_text").cast(docs.schema[c].dataType)
        out.append(old.alias(c))
    return kept.select(*out)

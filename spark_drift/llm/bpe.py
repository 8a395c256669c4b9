"""Byte-pair encoding as a deterministic automaton, and decoding by its arc labels.

The automaton reads token sequences and accepts exactly those that byte-pair
encoding can produce. It starts as one state with an arc per byte, each back to
that state. Every merge ``u v -> w`` then adds its gadget, in rank order: each
state whose ``u`` arc leads to a state with a ``v`` arc gains a ``w`` arc to the
place where ``v`` led; the ``u`` arcs are redirected to a copy of their target in
which the ``v`` arc is cut (for ``u = v`` the copy loses ``w`` as well). All arcs
of one label lead to one state, its *home*, so the automaton stays deterministic.

Written out, such a table has a row for most tokens and a column for each token.
Instead states are kept copy-on-write: a state knows its parent, the merge at
which it was copied and the arcs cut since; a token knows its two parts and the
merge that made it. Whether an arc exists follows from these small tables.

Words are read byte by byte through a second table, the first one determinised over
bytes. A row stands for all ways in which the bytes so far may go on: for each place
where a token may have begun, the state there and how far into the vocabulary's trie its
bytes lead. Of all token sequences that spell the bytes so far exactly one is accepted;
its last token is the row's label. A (row, byte) entry is worked out when first met and
looked up ever after, so a word costs one look-up a byte, and nothing is ever taken
back: the ids are the labels met, read from the word's end, each token's length back.

Edge cases: null and empty texts have no ids and decode to the empty text; the
text of the vocabulary's special tokens becomes their id, as the library has it;
texts and words of any length are taken whole; repeated rows repeat.
"""

from __future__ import annotations

import hashlib
import json
import re
import struct
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spark_drift.llm.batches import slices, texts

#: Unicode White_Space, as a character class
SPACES = "\\t\\n\\x0b\\x0c\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
#: entries kept by a worker: encoded words, arcs of the automaton, rows of the byte table
WORD_CACHE = 300_000
ARCS = 240_000
ROWS = 130_000


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies: printable
    Latin-1 bytes stand for themselves, the others follow from code point 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


@lru_cache(1)
def split_pattern() -> str:
    """The byte-level pre-split: contractions, letters, numbers, other marks, blanks.

    The library's letters and numbers are those of the Unicode version that
    ``unicodedata`` has here; newer code points of the regex module are taken out.
    """
    newer = [c for c in range(0x110000) if unicodedata.category(chr(c)) == "Cn"]
    known = regex.compile(r"[\p{L}\p{N}]")
    ranges: list[list[int]] = []
    for c in newer:
        if known.match(chr(c)):
            if ranges and ranges[-1][1] == c - 1:
                ranges[-1][1] = c
            else:
                ranges.append([c, c])
    not_yet = "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in ranges)
    minus = f"--[{not_yet}]" if not_yet else ""
    letter, number = f"[\\p{{L}}{minus}]", f"[\\p{{N}}{minus}]"
    other = f"[^{SPACES}[\\p{{L}}\\p{{N}}{minus}]]"
    return (
        f"(?V1)'s|'t|'re|'ve|'m|'ll|'d| ?{letter}+| ?{number}+| ?{other}+"
        f"|[{SPACES}]+(?![^{SPACES}])|[{SPACES}]+"
    )


#: from this code point on, letters and numbers are left to the full pattern
FAST_BELOW = 0x558


@lru_cache(1)
def fast_patterns() -> tuple[str, str]:
    """The same split for texts below ``FAST_BELOW``, and what finds a text that is not."""

    def listed(kind: str) -> str:
        return "".join(f"\\u{c:04x}" for c in range(FAST_BELOW) if unicodedata.category(chr(c))[0] == kind)

    letters, numbers, blanks = listed("L"), listed("N"), "\\t\\n\\x0b\\x0c\\r \\x85\\xa0"
    split = (
        f"'(?:[stmd]|re|ve|ll)| ?[{letters}]+| ?[{numbers}]+| ?[^{blanks}{letters}{numbers}]+"
        f"|[{blanks}]+(?![^{blanks}])|[{blanks}]+"
    )
    return split, f"[\\u{FAST_BELOW:04x}-\\U0010ffff]"


class MergeAutomaton:
    """Deterministic automaton over tokens, built merge by merge."""

    def __init__(self, labels: list[bytes], merges: list[tuple[int, int, int]]) -> None:
        """``labels``: bytes of each id. ``merges``: (left, right, result) ids by rank."""
        self.labels = labels
        size = len(labels)
        self.parts: list[tuple[int, int] | None] = [None] * size
        self.made = [0] * size  # merge number that made a token
        self.home = [-1] * size  # state behind all arcs with that label
        self.parent, self.copied = [-1], [0]
        self.cuts: dict[tuple[int, int], int] = {}
        self.arcs: dict[int, bool] = {}
        results = {w for _, _, w in merges}
        if len(results) != len(merges):
            raise ValueError("two merges make the same token")
        sharing = [1]  # labels at home in a state; the start is never given up
        for t, label in enumerate(labels):
            if len(label) == 1 and t not in results:
                self.home[t] = 0
                sharing[0] += 1
        for rank, (u, v, w) in enumerate(merges, 1):
            target = self.home[u]
            if target < 0 or self.home[v] < 0 or not self._arc(target, v, rank - 1):
                continue  # no path spells u v: the result has no arc
            self.parts[w], self.made[w] = (u, v), rank
            self.home[w] = self.home[v]
            sharing[self.home[w]] += 1
            if sharing[target] > 1:
                sharing[target] -= 1
                self.parent.append(target)
                self.copied.append(rank)
                sharing.append(1)
                target = self.home[u] = len(self.parent) - 1
            self.cuts[target, v] = rank
            if u == v:
                self.cuts[target, w] = rank
        self.arcs.clear()
        self.sizes = [len(x) for x in labels]
        #: trie of the labels that arcs carry: (node, byte) -> node, and the token that ends at a node
        self.trie: dict[int, int] = {}
        self.ends, self.deeper = [-1], [False]
        for t in range(size):
            if self.home[t] < 0:
                continue
            node = 0
            for byte in labels[t]:
                after = self.trie.get(node << 8 | byte)
                if after is None:
                    self.deeper[node] = True
                    after = self.trie[node << 8 | byte] = len(self.ends)
                    self.ends.append(-1)
                    self.deeper.append(False)
                node = after
            self.ends[node] = t
        self.restart((0,), -1)

    def restart(self, begun: tuple[int, ...], label: int) -> None:
        """An empty byte table, whose row 0 is the start of a word; row 1 is the row given. A row
        lists its places as ``state << 24 | trie node``."""
        self.rows: list[tuple[int, ...]] = [(0,), begun]
        self.label = [-1, label]
        self.known = {self.rows[0]: 0}
        self.table: dict[int, int] = {}

    def _arc(self, state: int, label: int, at: int) -> bool:
        """Is there a ``label`` arc out of ``state`` after merge number ``at``?"""
        while True:
            when = self.cuts.get((state, label))
            if when is not None and when <= at:
                return False
            made = self.made[label]
            if state and self.copied[state] >= made:
                at = self.copied[state]
                state = self.parent[state]
            elif made:
                at = made - 1
                label = self.parts[label][0]
            else:
                return True

    def arc(self, state: int, label: int) -> bool:
        """The finished automaton's transition."""
        key = state << 24 | label
        known = self.arcs.get(key)
        if known is None:
            if len(self.arcs) >= ARCS:
                self.arcs.clear()
            known = self.arcs[key] = self._arc(state, label, 1 << 60)
        return known

    def _enter(self, row: int, byte: int) -> int:
        """Works out one entry of the byte table."""
        if len(self.rows) >= ROWS:
            self.restart(self.rows[row], self.label[row])
            row = 1
        begun, label = [], -1
        for place in self.rows[row]:
            state, node = place >> 24, self.trie.get((place & 0xFFFFFF) << 8 | byte)
            if node is None:
                continue
            token = self.ends[node]
            if token >= 0 and self.arc(state, token):
                label = token
            if self.deeper[node]:
                begun.append(state << 24 | node)
        if label < 0:
            raise ValueError("the vocabulary cannot spell this word")
        begun.append(self.home[label] << 24)
        key = (*begun, -1 - label)
        after = self.known.get(key)
        if after is None:
            after = self.known[key] = len(self.rows)
            self.rows.append(tuple(begun))
            self.label.append(label)
        self.table[row << 8 | byte] = after
        return after

    def encode(self, word: bytes) -> list[int]:
        labels = []
        row, look = 0, self.table.get
        for byte in word:
            after = look(row << 8 | byte)
            if after is None:
                after = self._enter(row, byte)
                look = self.table.get
            row = after
            labels.append(self.label[row])
        out, at, sizes = [], len(word), self.sizes
        while at:
            token = labels[at - 1]
            out.append(token)
            at -= sizes[token]
        out.reverse()
        return out


class Codec:
    """Whole texts to ids and back."""

    def __init__(self, automaton: MergeAutomaton, pattern: str, special: dict[str, int]) -> None:
        self.automaton, self.pattern, self.special = automaton, pattern, special
        self._ready = None

    def __getstate__(self):
        return self.__dict__ | {"_ready": None}

    def _prepare(self):
        automaton = self.automaton

        class Words(dict):
            """word -> ids as little-endian bytes; a miss runs the automaton."""

            def __missing__(self, word: str) -> bytes:
                if len(self) >= WORD_CACHE:
                    self.clear()
                found = automaton.encode(word.encode())
                ids = struct.pack(f"<{len(found)}I", *found)
                if len(word) <= 64:
                    self[word] = ids
                return ids

        marks = sorted(self.special, key=len, reverse=True)
        stops = regex.compile("(" + "|".join(map(regex.escape, marks)) + ")") if marks else None
        full, (fast, beyond) = regex.compile(self.pattern).findall, map(re.compile, fast_patterns())
        find = lambda text: fast.findall(text) if beyond.search(text) is None else full(text)
        self._ready = (Words(), find, stops)
        return self._ready

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        words, find, stops = self._ready or self._prepare()
        if stops is None or not any(m in text for m in self.special):
            return b"".join(map(words.__getitem__, find(text)))
        out = []
        for k, piece in enumerate(stops.split(text)):
            if k % 2:
                out.append(self.special[piece].to_bytes(4, "little"))
            else:
                out.extend(map(words.__getitem__, find(piece)))
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        labels = self.automaton.labels
        return b"".join(map(labels.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


#: settings of a vocabulary file that this encoder honours, and the values it knows (None: not set)
KNOWN = {
    "model": {
        "type": ("BPE",), "dropout": (None,), "unk_token": (None,), "continuing_subword_prefix": (None, ""), "end_of_word_suffix": (None, ""),
        "fuse_unk": (None, False), "byte_fallback": (None, False), "ignore_merges": (None, False),
    },
    "pre_tokenizer": {"type": ("ByteLevel",), "add_prefix_space": (False,), "use_regex": (None, True)},
    "added": {"single_word": (None, False), "lstrip": (None, False), "rstrip": (None, False)},
}


def refuse_others(spec: dict) -> None:
    """Raises for a file whose settings would give other ids than this encoder's."""
    if spec.get("normalizer") is not None:
        raise ValueError("vocabulary file: normalizers are not supported")
    parts = [("model", spec["model"]), ("pre_tokenizer", spec.get("pre_tokenizer") or {})]
    parts += [("added", x) for x in spec.get("added_tokens", [])]
    for part, settings in parts:
        for name, values in KNOWN[part].items():
            if settings.get(name) not in values:
                raise ValueError(f"vocabulary file: {part} has {name} = {settings.get(name)!r}; supported: {values}")


@lru_cache(4)
def compile_vocabulary(path: str) -> Codec:
    """The codec of a byte-level vocabulary file (tokenizers' JSON); other kinds are refused."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    refuse_others(spec)
    model, alphabet = spec["model"], byte_alphabet()
    special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
    ids = model["vocab"]
    labels = [b""] * (max([*ids.values(), *special.values()]) + 1)
    for text, t in ids.items():
        labels[t] = bytes(alphabet[c] for c in text)
    pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
    merges = [(ids[a], ids[b], ids[a + b]) for a, b in pairs]
    automaton = MergeAutomaton(labels, merges)
    for text, t in special.items():
        automaton.labels[t] = text.encode()
    return Codec(automaton, split_pattern(), special)


ENCODED = "n_tokens long, ids array<int>, ids_sha256 string, decoded_sha256 string"


def encode_documents(docs: DataFrame, keys: list[str], vocabulary: str | None = None, with_ids: bool = True) -> DataFrame:
    """``keys`` plus ``n_tokens, ids, ids_sha256, decoded_sha256`` per row.

    ``ids_sha256`` digests the ids as little-endian 32-bit integers,
    ``decoded_sha256`` the text decoded from them. The compiled automaton, whose
    size is that of the vocabulary, is broadcast.
    """
    spark: SparkSession = docs.sparkSession
    sent = spark.sparkContext.broadcast(compile_vocabulary(vocabulary or default_vocabulary()))
    source = docs.select(F.struct(*[F.col(f"`{k}`") for k in keys]).alias("row"), F.col("text").cast("string").alias("text"))
    added = [f for f in T._parse_datatype_string(ENCODED).fields if with_ids or f.name != "ids"]
    schema = T.StructType([source.schema["row"], *added])

    def run(batches):
        codec, sha = sent.value, hashlib.sha256
        for part in slices(batches, "text"):
            ids = [codec.encode(x) for x in texts(part)]
            sizes = np.array([len(x) // 4 for x in ids], dtype=np.int64)
            columns = [part.column(0), pa.array(sizes)]
            if with_ids:
                offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
                values = np.frombuffer(b"".join(ids), dtype="<i4")
                columns.append(pa.ListArray.from_arrays(pa.array(offsets), pa.array(values)))
            columns.append(pa.array([sha(x).hexdigest() for x in ids], pa.string()))
            columns.append(pa.array([sha(codec.decode(x).encode()).hexdigest() for x in ids], pa.string()))
            yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    return source.mapInArrow(run, schema).select("row.*", *[f.name for f in added])

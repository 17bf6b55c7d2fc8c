"""Byte-level BPE by prefix dynamic programming.

Every byte prefix of a piece has exactly one valid encoding, so it is enough to store, for each prefix, the last token of
that encoding. A token t may end prefix i if the prefix before t ends in a token a such that a and t stay apart when merged
together. The table grows to the right (append) and stays valid left of an edit (replace), so both re-encode only what
changed. The pieces of a text are its matches of the tokenizer's pattern; each is encoded by itself.

Nulls count as empty texts (no ids). Ids may repeat or be null: each row gets its own result. Other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import KEPT_CHARS, documents, short_batches, slices, worker_table

#: Entries of a worker's piece table and pair table before they start anew; bounds memory, not results.
MAX_PIECES, MAX_PAIRS = 200_000, 300_000
#: White space as the rank file's library reads \s (the Unicode property); Python's own \s also has \x1c-\x1f.
SPACE = r"\t-\r \x85\xa0  -     　"


class PrefixBPE:
    """Ranks of byte strings, with the prefix table algorithm over them."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.bytes_of = {v: k for k, v in ranks.items()}
        self.piece_re = regex.compile(pattern.replace(r"[^\s\p{L}\p{N}]", rf"[^{SPACE}\p{{L}}\p{{N}}]").replace(r"(?!\S)", rf"(?![^{SPACE}])").replace(r"\s+", rf"[{SPACE}]+"))
        # The same split by the faster engine, for texts without any character that the two engines class differently.
        self.quick_re = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
        self.odd_re = re.compile("[\x1c-\x1f²³¹¼-¾]|[^\x00-ɏ]")
        self.quick = pattern == "'s|'t|'re|'ve|'m|'ll|'d| ?\\p{L}+| ?\\p{N}+| ?[^\\s\\p{L}\\p{N}]+|\\s+(?!\\S)|\\s+"
        nodes, self.step, self.ends = {b"": 0}, {}, [None]
        for word in sorted(ranks):  # a trie in one dictionary: node * 256 + byte -> node
            for i in range(1, len(word) + 1):
                if word[:i] not in nodes:
                    nodes[word[:i]] = len(nodes)
                    self.ends.append(None)
                    self.step[nodes[word[: i - 1]] << 8 | word[i - 1]] = nodes[word[:i]]
            self.ends[nodes[word]] = ranks[word]
        self.halves: dict[int, tuple[int, int] | None] = {}
        self.spines: tuple[dict, dict] = ({}, {})
        self.pairs: dict[int, bool] = {}
        self.pieces: dict[str, bytes] = {}
        self.whole: dict[int, bool] = {}

    @classmethod
    def load(cls, path: str, pattern: str) -> PrefixBPE:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, pattern)

    def split_of(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; None for a token no merge makes (a single byte, or unreachable)."""
        if token not in self.halves:
            word = self.bytes_of[token]
            parts = [word[i : i + 1] for i in range(len(word))]
            while len(parts) > 2:
                best = min(((r, i) for i in range(len(parts) - 1) if (r := self.ranks.get(parts[i] + parts[i + 1])) is not None), default=None)
                if best is None:
                    break
                i = best[1]
                parts[i : i + 2] = [parts[i] + parts[i + 1]]
            self.halves[token] = (self.ranks[parts[0]], self.ranks[parts[1]]) if len(parts) == 2 else None
        return self.halves[token]

    def reachable(self, token: int) -> bool:
        """True if encoding the token's own bytes gives the token."""
        if token not in self.whole:
            self.whole[token] = len(self.bytes_of[token]) == 1 or self.split_of(token) is not None
        return self.whole[token]

    def spine(self, token: int, side: int) -> list[tuple[bytes, float]]:
        """The parts that touch the token's edge (side 0 left, 1 right) while it grows, each with the rank that ends it."""
        if token not in self.spines[side]:
            out, end, t = [], float("inf"), token
            while True:
                out.append((self.bytes_of[t], end))
                halves = self.split_of(t) if len(self.bytes_of[t]) > 1 else None
                if halves is None:
                    break
                end, t = t, halves[side]
            self.spines[side][token] = out
        return self.spines[side][token]

    def apart(self, a: int, b: int) -> bool:
        """True if a followed by b stays a, b: no part at a's right edge merges with one at b's left edge in time.

        Of merges with one rank the leftmost goes first, hence < towards a's own growth and <= towards b's.
        """
        for x, x_end in self.spine(a, 1):
            for y, y_end in self.spine(b, 0):
                r = self.ranks.get(x + y)
                if r is not None and r < x_end and r <= y_end:
                    return False
        return True

    def extend(self, data, last: list[int], start: int, offset: int = 0, stop: int | None = None) -> None:
        """Fills the prefix table up to `stop`: last[i - offset] becomes the last token of data[:i + 1], for i from `start` on.

        Entries before `start` must be right, those of a longest token's length at least; `last` grows in place."""
        n, step, ends, pairs = len(data) if stop is None else stop, self.step, self.ends, self.pairs
        last += [-1] * (n - offset - len(last))
        for i in range(max(0, offset, start - self.longest), n):
            if i > offset:
                before = last[i - 1 - offset]
            elif i:
                continue  # what ends here was entered when the part left of it was filled
            else:
                before = -1
            node = 0
            for j in range(i, n):
                node = step.get(node << 8 | data[j])
                if node is None:
                    break
                t = ends[node]
                if t is None or last[j - offset] >= 0:
                    continue
                if before < 0:
                    if self.reachable(t):
                        last[j - offset] = t
                    continue
                key = before << 24 | t
                ok = pairs.get(key)
                if ok is None:
                    if len(pairs) >= MAX_PAIRS:
                        pairs.clear()
                    ok = pairs[key] = self.reachable(t) and self.apart(before, t)
                if ok:
                    last[j - offset] = t

    @property
    def longest(self) -> int:
        if not hasattr(self, "_longest"):
            self._longest = max(map(len, self.ranks))
        return self._longest

    def ids_of(self, data: bytes, last: list[int]) -> list[int]:
        out, i = [], len(data)
        while i:
            t = last[i - 1]
            out.append(t)
            i -= len(self.bytes_of[t])
        return out[::-1]

    def encode_piece(self, data: bytes) -> list[int]:
        t = self.ranks.get(data)
        if t is not None:
            return [t]
        return self.ids_of(data, self.wanted(data))

    def wanted(self, data: bytes) -> list[int]:
        """The prefix table with only the entries that the whole piece's encoding needs, found longest token first.

        A prefix has one valid last token, so whichever way reaches it first is right and no prefix is entered twice.
        """
        n, step, ends, pairs = len(data), self.step, self.ends, self.pairs
        last, stack = [-1] * n, [(0, -1, -1)]
        while stack:
            i, t, before = stack.pop()
            if i:
                if last[i - 1] >= 0:
                    continue
                if before < 0:
                    if not self.reachable(t):
                        continue
                else:
                    key = before << 24 | t
                    ok = pairs.get(key)
                    if ok is None:
                        if len(pairs) >= MAX_PAIRS:
                            pairs.clear()
                        ok = pairs[key] = self.reachable(t) and self.apart(before, t)
                    if not ok:
                        continue
                last[i - 1] = t
                if i == n:
                    break
            node = 0
            for j in range(i, n):
                node = step.get(node << 8 | data[j])
                if node is None:
                    break
                if ends[node] is not None:
                    stack.append((j + 1, ends[node], t))
        return last

    def split(self, text: str) -> list[str]:
        return (self.quick_re if self.quick and not self.odd_re.search(text) else self.piece_re).findall(text)

    def encode_bytes(self, text: str) -> bytes:
        """The ids of a text as little-endian unsigned 32-bit integers."""
        pieces, known = self.split(text), self.pieces
        try:
            return b"".join(map(known.__getitem__, pieces))
        except KeyError:
            pass
        if len(known) >= MAX_PIECES:
            known.clear()
        long: dict[str, bytes] = {}
        for p in set(pieces):
            if p not in known:
                ids = self.encode_piece(p.encode())
                (known if len(p) <= KEPT_CHARS else long)[p] = struct.pack(f"<{len(ids)}I", *ids)
        return b"".join([known[p] if p in known else long[p] for p in pieces] if long else map(known.__getitem__, pieces))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_bytes(text), "<u4").tolist()

    def decode(self, ids) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


class PrefixTable:
    """One piece with its prefix table: exact ids after appends and edits. Only what changed is encoded anew, in place; an edit
    moves the bytes and entries after it where its length changes."""

    def __init__(self, bpe: PrefixBPE, data: bytes = b""):
        self.bpe, self.data, self.last = bpe, bytearray(data), []
        bpe.extend(self.data, self.last, 0)

    def append(self, more: bytes) -> PrefixTable:
        start = len(self.data)
        self.data += more
        self.bpe.extend(self.data, self.last, start)
        return self

    def replace(self, start: int, end: int, by: bytes) -> PrefixTable:
        """Put `by` in place of bytes start to end. Left of the edit the table stands; right of it, it is kept again once
        the new last tokens agree with the old ones over a longest token's length."""
        keep, shift = self.bpe.longest, len(by) - (end - start)
        self.data[start:end] = by
        n, offset = len(self.data), max(0, start - keep - 1)
        new, at = self.last[offset:start], start
        while at < n:
            upto = min(n, max(at, start + len(by)) + 2 * keep)
            self.bpe.extend(self.data, new, at, offset, upto)
            at = upto
            tail = at - keep
            if tail >= start + len(by) and at < n and new[tail - offset :] == self.last[tail - shift : at - shift]:
                break
        self.last[offset : at - shift if at < n else len(self.last)] = new
        return self

    def ids(self) -> list[int]:
        return self.bpe.ids_of(self.data, self.last)


def loaded(path: str, pattern: str) -> PrefixBPE:
    """This worker's encoder, kept between tasks."""
    table = worker_table("bpe")
    if (path, pattern) not in table:
        table.clear()
        table[path, pattern] = PrefixBPE.load(path, pattern)
    return table[path, pattern]


def encode(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """Per row: id, n_tokens, ids (little-endian u32 binary, if keep_ids), ids_sha256, decoded_sha256.

    Null text: no tokens, digests of nothing. ranks_path must be readable on every worker.
    """
    source = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = source.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_tokens bigint, {'ids binary, ' if keep_ids else ''}ids_sha256 string, decoded_sha256 string"

    short_batches(docs.sparkSession)

    def run(batches):
        bpe = loaded(ranks_path, pattern)
        for b in slices(batches):
            packed = [bpe.encode_bytes(t) if t else b"" for t in b.column(1).to_pylist()]
            columns = [b.column(0), pa.array([len(x) >> 2 for x in packed], pa.int64())]
            if keep_ids:
                columns.append(pa.array(packed, pa.binary()))
            columns.append(pa.array([hashlib.sha256(x).hexdigest() for x in packed], pa.string()))
            columns.append(pa.array([hashlib.sha256(bpe.decode(np.frombuffer(x, "<u4").tolist())).hexdigest() for x in packed], pa.string()))
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", *["ids"] * keep_ids, "ids_sha256", "decoded_sha256"])

    return source.mapInArrow(run, schema)


def op5_bpe_prefix_dp(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as tokenizers

    return encode(documents(spark, sf_dir), tokenizers.path("byte_bpe_50k.tiktoken"), tokenizers.PATTERN, keep_ids=False)

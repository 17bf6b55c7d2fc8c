"""Token ids in binary files: frequency-ranked, byte-aligned variable length, control bytes apart from the data bytes.

Ids are replaced by their rank in the corpus (the commonest id is 0), so most values fit one byte. A value takes one to four
bytes; its length minus one is two bits of a control byte, four values a control byte. Control and data bytes are kept apart, so
that a block is decoded at once: a table gives the four lengths of each control byte, and a mask puts the data in place.

Files: Parquet rows, one a block of documents in ascending id order, with part, block, the part's ids before the block, the
documents' ids and token counts, control and data; beside them `ranks` (rank -> id) and `starts` (ids of all parts before).
Ids ascend over parts and blocks; null ids come first; rows with one id are ordered by their tokens.

Null texts have the end id only. Empty tables give empty files.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from array import array
from operator import attrgetter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import KEPT_CHARS, documents, materialise, short_batches, slices, worker_table

#: Words and pieces of a worker's table before it starts anew.
MAX_PIECES = 300_000
#: Rows of a part and ids of a block, about.
PART_ROWS, BLOCK_ROWS = 50_000, 500
LENGTHS = (np.arange(256)[:, None] >> np.array([0, 2, 4, 6]) & 3).astype(np.uint8) + 1
PLACES = np.arange(4, dtype=np.uint8)
ID = attrgetter("id")
#: Fixed values of byte-level tokenizers: printable Latin-1 bytes stand for themselves, the others for U+0100 on.
_PLAIN = [*range(33, 127), *range(161, 173), *range(174, 256)]
BYTE_LETTERS = {b: chr(256 + n) for n, b in enumerate(b for b in range(256) if b not in _PLAIN)}


def pack(values: np.ndarray) -> tuple[bytes, bytes]:
    """(control, data) of unsigned 32-bit values."""
    v = np.ascontiguousarray(values, "<u4")
    padded = np.zeros(-(-len(v) // 4) * 4, np.uint8)
    extra = padded[: len(v)]
    extra += v >= 1 << 8
    most = int(v.max(initial=0))
    if most < 1 << 16:
        wide = v.astype("<u2").view(np.uint8).reshape(-1, 2)
    else:
        extra += v >= 1 << 16
        extra += v >= 1 << 24
        wide = v.view(np.uint8).reshape(-1, 4)
    four = padded.reshape(-1, 4)
    control = four[:, 0] | four[:, 1] << 2 | four[:, 2] << 4 | four[:, 3] << 6
    return control.tobytes(), wide[PLACES[: wide.shape[1]] <= extra[:, None]].tobytes()


def unpack(control: bytes, data: bytes, n: int) -> np.ndarray:
    size = LENGTHS[np.frombuffer(control, np.uint8)].ravel()[:n]
    width = 2 if size.max(initial=1) <= 2 else 4
    out = np.zeros((n, width), np.uint8)
    out[PLACES[:width] < size[:, None]] = np.frombuffer(data, np.uint8)
    return out.view(f"<u{width}").ravel().astype("<u4", copy=False)


class PieceTokenizer:
    """A tokenizer of the tokenizers library with a table of pieces.

    Texts of plain Latin letters are cut at white space and looked up word by word. A word not in the table is split as the
    tokenizer's own pattern does; pieces not in the table are encoded by the library. All other texts go through the library
    whole, and so does every text if the file's normaliser, splitter, model or special tokens are not of the kind that RULES states.
    """

    #: Fixed values of the file format: rules under which words and pieces may be looked up one by one.
    RULES = {
        "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]},
        "pre_tokenizer": {
            "type": "Sequence",
            "pretokenizers": [
                {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True},
                {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
            ],
        },
        "truncation": None,
        "padding": None,
    }

    #: The pieces of those rules after lower-casing, for characters below U+0250.
    PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+")
    ODD = re.compile("[\x1c-\x1f²³¹¼-¾İ]|[^\x00-ɏ]")
    #: Of these, the ones in Latin-1: seven searches for a character cost less than one for a class.
    ODD_LATIN = "\x1c\x1d\x1e\x1f²³¹¼½¾"

    def __init__(self, path: str, code: str = "I"):
        """code: array type of the ids, "I" for four bytes, "H" for two."""
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        rules = json.loads(self.tokenizer.to_str())
        known = all(rules.get(k) == v for k, v in self.RULES.items()) and rules["model"]["type"] == "BPE" and not rules["model"].get("dropout")
        self.by_words = known and not any(t["single_word"] or t["normalized"] for t in rules["added_tokens"])
        self.code, self.pieces = code, {}

    def plain(self, text: str) -> bool:
        """True if the text's words may be looked up."""
        if not self.by_words:
            return False
        try:
            text.isascii() or text.encode("latin-1")
            odd = any(c in text for c in self.ODD_LATIN)
        except UnicodeEncodeError:
            odd = self.ODD.search(text) is not None
        return not odd and not any(s in text for s in self.special)

    def _encode(self, text: str) -> bytes:
        return array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _encode_piece(self, piece: str) -> bytes:
        """A piece needs no normalising or splitting any more: the library's model gets its bytes in the byte-level alphabet."""
        written = piece if piece.isascii() and piece.isprintable() else piece.encode().decode("latin-1").translate(BYTE_LETTERS)
        return array(self.code, map(ID, self.model.tokenize(written))).tobytes()

    def _word(self, word: str) -> bytes:
        """Ids of a word, all pieces of which are noted."""
        known, parts = self.pieces, []
        for p in self.PIECE.findall(word):
            ids = known.get(p)
            if ids is None:
                ids = self._encode_piece(p)
                if len(p) <= KEPT_CHARS:
                    known[p] = ids
            parts.append(ids)
        return b"".join(parts)

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as unsigned integers of this machine's (little-endian) order."""
        if len(self.pieces) >= MAX_PIECES:
            self.pieces.clear()
        known, out = self.pieces, []
        for t in texts:
            if not t:
                out.append(b"")
                continue
            if not self.plain(t):
                out.append(self._encode(t))
                continue
            words = t.lower().split()
            found, at = list(map(known.get, words)), -1
            for _ in range(found.count(None)):
                at = found.index(None, at + 1)
                w = words[at]
                ids = known.get(w)  # it may have come earlier in this text
                if ids is None:
                    ids = self._encode_piece(w) if w.isalpha() else self._word(w)
                    if len(w) <= KEPT_CHARS:
                        known[w] = ids
                found[at] = ids
            out.append(b"".join(found))
        return out


def tokenizer_of(path: str, code: str) -> PieceTokenizer:
    table = worker_table("token_files")
    if (path, code) not in table:
        table.clear()
        table[path, code] = PieceTokenizer(path, code)
    return table[path, code]


def tokenize(docs: DataFrame, path: str, end_id: int, n_ids: int, wide: bool, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, h (of the ids, to order rows alike in id), ids (two bytes each, four if wide); and rows marked `counts` whose ids
    hold how often each id occurs in a task's texts (eight bytes each), so that nothing is read twice for the ranks."""
    source = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = source.schema["doc_id"].dataType.simpleString()
    code = "I" if wide else "H"
    end = array(code, [end_id]).tobytes()
    short_batches(docs.sparkSession)

    def rows(doc_ids, ids, counts):
        return pa.RecordBatch.from_arrays([doc_ids, pa.array(map(zlib.crc32, ids), pa.int64()), pa.array(ids, pa.binary()), pa.array([counts] * len(ids))], names=["doc_id", "h", "ids", "counts"])

    def run(batches):
        tok, total, last = tokenizer_of(path, code), np.zeros(n_ids, np.int64), None
        for b in slices(batches):
            ids = [x + end for x in tok.encode(b.column(1).to_pylist())]
            total += np.bincount(np.frombuffer(b"".join(ids), code), minlength=n_ids)
            yield rows(b.column(0), ids, False)
            last = b.column(0).type
        if last is not None:
            yield rows(pa.nulls(1, last), [total.tobytes()], True)

    return source.mapInArrow(run, f"doc_id {kind}, h bigint, ids binary, counts boolean")


def ranked(tokens: DataFrame, n_ids: int) -> np.ndarray:
    """rank -> id by falling corpus frequency, then id; all n_ids ids. n_ids numbers reach the driver."""

    def run(batches):
        total = np.zeros(n_ids, np.int64)
        for b in batches:
            for x in b.column(0):
                total += np.frombuffer(x.as_buffer(), np.int64)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["id", "n"])

    counted = tokens.where("counts").select("ids").mapInArrow(run, "id int, n bigint").groupBy("id").agg(F.sum("n").alias("n")).toArrow()
    total = np.zeros(n_ids, np.int64)
    total[counted["id"].to_numpy()] = counted["n"].to_numpy()
    return np.lexsort((np.arange(n_ids), -total)).astype("<u4")


class TokenFiles:
    """Written token files: blocks, starts of parts, rank -> id."""

    def __init__(self, blocks: DataFrame, starts: DataFrame, ids: np.ndarray):
        self.blocks, self.starts, self.ids = blocks, starts, ids

    @classmethod
    def write(cls, tokens: DataFrame, ids: np.ndarray, wide: bool) -> TokenFiles:
        tokens = tokens.where("not counts")
        spark, n = tokens.sparkSession, tokens.count()
        rank = np.empty(len(ids), "<u4")
        rank[ids] = np.arange(len(ids))
        sent = spark.sparkContext.broadcast(rank)
        small = "<u4" if wide else "<u2"
        kind = tokens.schema["doc_id"].dataType.simpleString()
        parts = max(1, min(n, max(int(spark.conf.get("spark.sql.shuffle.partitions")), n // PART_ROWS)))
        rows = tokens.repartitionByRange(parts, "doc_id", "h").sortWithinPartitions("doc_id", "h", "ids").withColumn("part", F.spark_partition_id())

        def run(batches):
            worker_table("token_blocks")  # lets the tokenizer go
            before, number = 0, 0
            for b in slices(batches, BLOCK_ROWS):
                if not b.num_rows:
                    continue
                packed = b.column(1)
                ends = np.frombuffer(packed.buffers()[1], np.int32, len(packed) + 1, packed.offset * 4)
                values = np.frombuffer(packed.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(small)
                control, data = pack(sent.value[values])
                counts = (np.diff(ends) // (4 if wide else 2)).tolist()
                yield pa.RecordBatch.from_arrays(
                    [b.column(2).slice(0, 1), pa.array([number]), pa.array([before]), pa.array([len(values)]), pa.array([b.column(0).to_pylist()], pa.list_(b.column(0).type)), pa.array([counts], pa.list_(pa.int64())), pa.array([control], pa.binary()), pa.array([data], pa.binary())],
                    names=["part", "block", "before", "n_ids", "doc_ids", "counts", "control", "data"],
                )
                before, number = before + len(values), number + 1

        schema = f"part int, block bigint, before bigint, n_ids bigint, doc_ids array<{kind}>, counts array<bigint>, control binary, data binary"
        short_batches(spark)
        blocks = materialise(rows.select("doc_id", "ids", "part").mapInArrow(run, schema), "token-blocks")
        totals = blocks.groupBy("part").agg(F.sum("n_ids").alias("n"))  # one row a part
        starts = totals.select("part", F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("start"))
        return cls(blocks, materialise(starts, "token-starts"), ids)

    def _documents(self, names: list[str], types: str, made) -> DataFrame:
        """Reads the files block by block; made(ids, ends, counts) gives the columns beside doc_id and start."""
        sent = self.blocks.sparkSession.sparkContext.broadcast(self.ids)
        kind = self.blocks.schema["doc_ids"].dataType.elementType.simpleString()

        def run(batches):
            worker_table("token_blocks")
            for b in batches:
                for at in range(b.num_rows):
                    row = {k: b.column(i)[at] for i, k in enumerate(b.schema.names)}
                    ids = sent.value[unpack(row["control"].as_buffer(), row["data"].as_buffer(), row["n_ids"].as_py())]
                    counts = row["counts"].values.to_numpy()
                    ends = np.cumsum(counts)
                    yield pa.RecordBatch.from_arrays([row["doc_ids"].values, pa.array(row["first"].as_py() + ends - counts), *made(ids, ends, counts)], names=["doc_id", "start", *names])

        located = self.blocks.join(F.broadcast(self.starts), "part").withColumn("first", F.col("before") + F.col("start"))
        return located.select("first", "n_ids", "doc_ids", "counts", "control", "data").mapInArrow(run, f"doc_id {kind}, start bigint, {types}")

    def read(self) -> DataFrame:
        """One row a document, from the files: doc_id, start (ids of all documents before it), ids (binary, u32)."""

        def made(ids, ends, counts):
            return [pa.array([ids[e - c : e].tobytes() for e, c in zip(ends, counts)], pa.binary())]

        return self._documents(["ids"], "ids binary", made)

    def digests(self) -> DataFrame:
        """doc_id, start, n_tokens, ids_crc32, from the files."""

        def made(ids, ends, counts):
            return [pa.array(counts, pa.int64()), pa.array([zlib.crc32(ids[e - c : e]) for e, c in zip(ends, counts)], pa.int64())]

        return self._documents(["n_tokens", "ids_crc32"], "n_tokens bigint, ids_crc32 bigint", made)


def write_corpus(docs: DataFrame, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> TokenFiles:
    from tokenizers import Tokenizer

    n_ids = max(Tokenizer.from_file(path).get_vocab_size(with_added_tokens=True), end_id + 1)
    wide = n_ids > 1 << 16
    tokens = materialise(tokenize(docs, path, end_id, n_ids, wide, id_col, text_col), "token-ids", "snappy")
    return TokenFiles.write(tokens, ranked(tokens, n_ids), wide)


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as tokenizers

    return write_corpus(documents(spark, sf_dir), tokenizers.path("word_bpe_49k.json"), 2).digests()

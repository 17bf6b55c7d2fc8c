"""SimHash near-duplicates with a Gray-order hierarchical index for the Hamming join.

Fingerprints that differ in at most `distance` bits agree in one of distance + 1 blocks of bits at least. Each distinct fingerprint is dealt once for
each block, turned so that the block leads, and the turned fingerprints are ranged by Gray rank: a task owns a range of leading blocks. It sorts
what it has by Gray rank, so that neighbours share most bits, and factors the shared bits (mask and pattern) of runs of FAN neighbours into upper
nodes, up to a single root. The join starts with the root against itself and goes down: of two nodes, the bits that both have fixed are compared, a
difference in the leading block or more than `distance` accumulated differences prune the two groups as a whole, and only newly fixed bits are
counted on the next level. A leading block that more than TASK_ROWS fingerprints share is cut into parts, of which every two meet in a task.
Each task sends on only a spanning forest of its links, which loses no connection; components are found by alternating
star contractions with tables on shared files between the rounds.

Rows with one fingerprint are one node however many they are. Null and empty texts have fingerprint zero, linked like any
other. Ids may be null (never a component's id unless all of it are null) or repeat. Empty tables give empty results.

`keep_one`, the pipeline's stage, links texts whose sets of five-word shingles have a Jaccard similarity of 0.8 at least. Fingerprints of such texts may be
ten bits apart and more, beyond what any index of 64 bits finds without loss. So the SimHash index goes first: what it links (and texts of one
fingerprint) is checked on the whole sets and connected. Then a complete search goes over what is not connected yet. In any fixed order
of all shingles, the first
fifth (and one) of two such sets have a shingle in common; the order is by falling rarity, from a table of counts by hash, so
that common lines come last. Candidates are checked on the whole sets. Within the texts that have a first shingle in common,
some pivots are compared with all others first, then more of them, but only with texts not yet connected with the pivot, until
each pair is compared or connected: a large group of copies costs pairs in proportion to its size.
"""

from __future__ import annotations

import uuid
from itertools import accumulate

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checked, documents, drop_tables, keys_of, materialise, salted_join, short_batches, slices, without

FAN, CHUNK = 8, 100_000
#: Dealt fingerprints a task takes in the Hamming join (24 bytes each), about.
TASK_ROWS = 1_000_000
#: Of keep_one: words of a shingle, least Jaccard similarity as a fraction, pivots of the first round.
SHINGLE, SIMILAR, FIRST_PIVOTS = 5, (4, 5), 16
#: Buckets in which a set's shingles are counted, rows of one key beyond which they are sent along, and first keys sent with each row.
BUCKETS, WIDE, HEADS = 128, 4, 8
#: Counters of shingles, by the leading bits of their hashes, and rows in which a task sends them.
COUNTERS, SECTIONS, COUNTER_SHIFT = 1 << 20, 16, np.uint64(44)
#: Odd multipliers: of the polynomial in a shingle's words, and of the two rounds that mix its bits.
SPREAD = np.array([0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB], np.uint64)
BYTE_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.int64)


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """64 bits: each set if set in over half of the hashes of the text's shingles, repeats included."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return 0
    joined, n = b" ".join(words), len(words)
    h = xxhash.xxh64_digest
    if n <= shingle:
        digests, n = h(joined, seed), 1
    else:
        ends = [e - 1 for e in accumulate(len(w) + 1 for w in words)]
        starts = [0, *[e + 1 for e in ends[: n - shingle]]]
        digests = b"".join([h(joined[s:e], seed) for s, e in zip(starts, ends[shingle - 1 :], strict=True)])
        n -= shingle - 1
    # Count each byte value at each of the eight byte places, then the bits of the byte values.
    places = np.frombuffer(digests, np.uint8).reshape(n, 8) + np.arange(0, 2048, 256)
    ones = np.einsum("pv,vb->pb", np.bincount(places.ravel(), minlength=2048).reshape(8, 256), BYTE_BITS)
    return int.from_bytes(np.packbits(ones.ravel() * 2 > n).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text", more: list | None = None) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long), and `more` columns unchanged."""
    source = docs.select(F.col(text_col).alias("_whole_text"), F.col(id_col).alias("doc_id"), *(more or []))
    short_batches(docs.sparkSession)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in source.schema[1:]) + ", fp bigint"

    def run(batches):
        for b in slices(batches, 500):
            fp = np.array([fingerprint(t, shingle) for t in b.column(0).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(fp)], names=[*b.schema.names[1:], "fp"])

    return source.mapInArrow(run, schema)


def gray_rank(x: np.ndarray) -> np.ndarray:
    """The place of x in the Gray code's order; its leading bits depend on x's leading bits only."""
    x = x.copy()
    for s in (1, 2, 4, 8, 16, 32):
        x ^= x >> np.uint64(s)
    return x


def turned(fp: np.ndarray, bits: int | np.ndarray) -> np.ndarray:
    """Each value's bits moved up by `bits`, the leading ones to the end."""
    bits = np.broadcast_to(np.asarray(bits, np.uint64), fp.shape)
    return fp << bits | np.where(bits > 0, fp >> (np.uint64(64) - np.maximum(bits, np.uint64(1))), np.uint64(0))


class GrayIndex:
    """Groups of values (group numbers ascend) in Gray order with mask-and-pattern nodes above them, up to one root a group."""

    def __init__(self, group: np.ndarray, fp: np.ndarray, fan: int = FAN):
        self.fp, self.fan = fp, fan
        start = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]) if len(fp) else np.zeros(0, np.int64)
        #: Per level: pattern, mask, first child, end of children. Level 0: the values.
        self.levels = [(fp, np.full(len(fp), ~np.uint64(0)), None, None)]
        every, some, own = fp, fp, group
        while len(own) > len(start):
            first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
            size = np.diff(np.r_[first, len(own)])
            place = np.arange(len(own)) - np.repeat(first, size)
            low = np.flatnonzero(place % fan == 0)
            every, some, own = np.bitwise_and.reduceat(every, low), np.bitwise_or.reduceat(some, low), own[low]
            self.levels.append((every, every | ~some, low, np.r_[low[1:], len(place)]))

    def links(self, distance: int, lead: np.ndarray | None = None):
        """Yields arrays (i, j), i < j, of positions within one group at most `distance` bits apart. lead: bits of each root's group that must agree."""
        self.compared = 0
        top = len(self.levels) - 1
        n = len(self.levels[top][0])
        lead = np.zeros(n, np.uint64) if lead is None else lead
        everyone = np.arange(n)
        # Level, the two nodes, the root, and the differences among the bits that both nodes have fixed.
        stack = [(top, everyone[s : s + CHUNK], everyone[s : s + CHUNK], everyone[s : s + CHUNK], np.zeros(len(everyone[s : s + CHUNK]), np.uint8)) for s in range(0, n, CHUNK)]
        while stack:
            level, a, b, root, differ = stack.pop()
            if level == 0:
                if len(a):
                    yield a, b
                continue
            _, above, low, end = self.levels[level]
            pattern, mask, _, _ = self.levels[level - 1]
            known = above[a] & above[b]
            na, nb = end[a] - low[a], end[b] - low[b]
            for s in range(0, len(a), max(1, CHUNK // self.fan)):
                cut = slice(s, s + max(1, CHUNK // self.fan))
                total = na[cut] * nb[cut]
                k = np.repeat(np.arange(len(total)), total)
                at = np.arange(total.sum()) - np.repeat(np.cumsum(total) - total, total)
                x, y = low[a[cut]][k] + at // nb[cut][k], low[b[cut]][k] + at % nb[cut][k]
                good = (x < y) if level == 1 else (x <= y)
                x, y, k = x[good], y[good], k[good]
                self.compared += len(x)
                new = (pattern[x] ^ pattern[y]) & mask[x] & mask[y] & ~known[cut][k]
                so_far = differ[cut][k] + np.bitwise_count(new)
                near = (so_far <= distance) & (new & lead[root[cut][k]] == 0)
                stack.append((level - 1, x[near], y[near], root[cut][k][near], so_far[near]))


def forest(n: int, pairs) -> np.ndarray:
    """For positions 0..n-1 the smallest position each is linked to, over all arrays of pairs."""
    parent = np.arange(n)
    for i, j in pairs:
        while True:
            a, b = parent[i], parent[j]
            differ = a != b
            if not differ.any():
                break
            i, j, a, b = i[differ], j[differ], a[differ], b[differ]
            np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
            while (parent[parent] != parent).any():
                parent = parent[parent]
    return parent


def spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, ... of each run, one after another."""
    return np.arange(size.sum()) - np.repeat(np.cumsum(size) - size - start, size)


def gray_column(x, bits: int):
    """Gray rank of a column of numbers of so many bits."""
    s = 1
    while s < bits:
        x = x.bitwiseXOR(F.shiftright(x, s))
        s *= 2
    return x


def near_links(distinct: DataFrame, n: int, distance: int = 2) -> DataFrame:
    """Links (a, b) over distinct fingerprints `fp`: a spanning forest of each task's links of at most `distance` bits."""
    cuts = [64 * k // (distance + 1) for k in range(distance + 2)]
    width = [b - a for a, b in zip(cuts, cuts[1:])]
    blocks = F.array(*[gray_column(F.shiftrightunsigned("fp", 64 - cuts[k + 1]).bitwiseAND((1 << width[k]) - 1), width[k]) for k in range(len(width))])
    dealt = distinct.select("fp", F.posexplode(blocks).alias("block", "rank"))
    conf = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = max(conf, n * len(width) // TASK_ROWS)
    keys = ["block", "rank", "i", "j"]
    dealt = dealt.withColumns({"i": F.lit(0), "j": F.lit(0)})
    if n > TASK_ROWS:  # only then a leading block can have that many
        hot = dealt.groupBy("block", "rank").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > TASK_ROWS).select("block", "rank", F.ceil(F.col("n") / TASK_ROWS).cast("int").alias("parts"))
        hot = materialise(hot, "hot-blocks")  # n * blocks / TASK_ROWS rows at most
        if not hot.isEmpty():
            own = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
            met = dealt.drop("i", "j").join(checked(hot, n * len(width) // TASK_ROWS, 24), ["block", "rank"], "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
            met = met.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
            dealt = met.select("fp", "block", "rank", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
    dealt = dealt.repartitionByRange(parts, *keys)

    def run(batches):
        got = [[b.column(c).to_numpy() for c in range(4)] for b in batches if b.num_rows]
        if not got:
            return
        fp, block, i, j = (np.concatenate(x) for x in zip(*got))
        del got
        value = turned(fp.view(np.uint64), np.array(cuts[:-1])[block])
        order = np.lexsort((gray_rank(value), j, i, block))
        value, block, i, j = value[order], block[order], i[order], j[order]
        group = np.cumsum(np.r_[False, (block[1:] != block[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])])
        first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        lead = np.array([~np.uint64(0) << np.uint64(64 - w) for w in width], np.uint64)[block[first]]
        parent = forest(len(value), GrayIndex(group, value).links(distance, lead))
        own = np.flatnonzero(parent != np.arange(len(value)))
        back = np.array([(64 - c) % 64 for c in cuts[:-1]])
        a, b = turned(value[own], back[block[own]]), turned(value[parent[own]], back[block[own]])
        yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    return dealt.select("fp", F.col("block").cast("long"), F.col("i").cast("long"), F.col("j").cast("long")).mapInArrow(run, "a bigint, b bigint").distinct()


def components(links: DataFrame) -> DataFrame:
    """node, root (the smallest node it is connected with) for all nodes of links (a, b); alternating star contractions."""
    edges = materialise(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    n, before = edges.count(), None

    def star(edges: DataFrame, n: int, both: bool) -> DataFrame:
        ways = edges.select("u", "v")
        if both:  # large star: larger neighbours go to the smallest neighbour
            ways = ways.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = ways.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")).withColumn("m", F.least("m", "u"))
        joined = salted_join(ways, least, ["u"], "n", n, 24)
        if both:
            moved = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        else:  # small star: smaller neighbours and the node itself go to the smallest
            moved = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(least.select("u", F.col("m").alias("v")))
        return moved.where("u <> v").distinct()

    while n:
        edges = materialise(star(materialise(star(edges, 2 * n, True), "large-star"), n, False), "edges")
        state = edges.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("h"), F.sum(F.hash("u", "v").cast("long")).alias("s")).first()
        n = state["n"]
        if state == before:
            break
        before = state
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionAll(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def grouped(rows: DataFrame, distance: int = 2, links: DataFrame | None = None) -> DataFrame:
    """rows (doc_id, fp, ...; on shared files) with component_id: the smallest doc_id reachable, its own included. links: (a, b)
    over fp; without them, fingerprints at most `distance` bits apart are linked."""
    nodes = materialise(rows.groupBy("fp").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("least")), "fingerprints")
    n = nodes.count()
    roots = materialise(components(near_links(nodes.select("fp"), n, distance) if links is None else links), "components")
    n_roots = roots.count()
    placed = nodes.join(checked(roots.withColumnRenamed("node", "fp"), n_roots, 24), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    linked = placed.join(checked(roots.select("root").distinct().withColumn("linked", F.lit(True)), n_roots, 16), "root", "left")
    ids = linked.where("linked").groupBy("root").agg(F.min("least").alias("component_id"), F.count(F.lit(1)).alias("parts"))
    alone = linked.where("linked is null").select("fp", "n", F.col("least").alias("component_id"))
    told = salted_join(linked.where("linked").drop("linked"), materialise(ids, "component-ids"), ["root"], "parts", n_roots, 32)
    labels = materialise(alone.unionAll(told.select("fp", "n", "component_id")), "labels")
    return salted_join(rows, labels, ["fp"], "n", n, 40)


def classify(docs: DataFrame, shingle: int = 3, distance: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row: doc_id, fingerprint (hex), component_id."""
    rows = materialise(fingerprints(docs, shingle, id_col, text_col), "simhash")
    return grouped(rows, distance).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def bits_of(digests: np.ndarray) -> int:
    """SimHash of 64-bit hashes: each bit set if set in over half of them."""
    places = digests.astype(">u8").view(np.uint8).reshape(-1, 8) + np.arange(0, 2048, 256)
    ones = np.einsum("pv,vb->pb", np.bincount(places.ravel(), minlength=2048).reshape(8, 256), BYTE_BITS)
    return int.from_bytes(np.packbits(ones.ravel() * 2 > len(digests)).tobytes(), "big")


def shingles(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """The set of hashes of the text's shingles, ascending; a text of fewer words is one shingle, none is the empty set.

    A shingle's hash is a polynomial in its words' hashes, with the bits mixed, so that each word is hashed once only."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    k = min(shingle, len(w))
    h = np.full(len(w) - k + 1, k, np.uint64)
    for i in range(k):
        h = h * SPREAD[0] + w[i : len(w) - k + 1 + i]
    for by, times in zip((30, 27), SPREAD[1:], strict=True):
        h = (h ^ (h >> np.uint64(by))) * times
    h = np.sort(h ^ (h >> np.uint64(31)))
    return h[np.r_[True, h[1:] != h[:-1]]]


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Jaccard similarity of two sets at least SIMILAR, in whole numbers."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * SIMILAR[1] >= (len(a) + len(b) - both) * SIMILAR[0]


def bucket_counts(shingles_: np.ndarray) -> bytes:
    """How many shingles of a set fall in each of BUCKETS, 255 at most. What two sets' counts differ by, summed up, is no more than the shingles
    that only one of them has."""
    return np.minimum(np.bincount((shingles_ % np.uint64(BUCKETS)).astype(np.intp), minlength=BUCKETS), 255).astype(np.uint8).tobytes()


def node_of(shingles_: np.ndarray) -> int:
    """A hash of the set: equal sets are one node."""
    return xxhash.xxh64_intdigest(shingles_.tobytes(), 7)


def shingle_sets(docs: DataFrame, shingle: int, id_col: str, text_col: str, more: list) -> DataFrame:
    """doc_id, `more` columns, fp (the set's node), sim (its SimHash), counts (bucket_counts). The sets themselves, larger than the texts, are made anew where they are needed."""
    source = docs.select(F.col(text_col).alias("_whole_text"), F.col(id_col).alias("doc_id"), *more)
    short_batches(docs.sparkSession)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in source.schema[1:]) + ", fp bigint, sim bigint, counts binary"

    def run(batches):
        for b in slices(batches, 200):
            found = [shingles(t, shingle) for t in b.column(0).to_pylist()]
            sim = np.array([bits_of(x) for x in found], np.uint64).view(np.int64)
            fp = np.array([node_of(x) for x in found], np.uint64).view(np.int64)
            counts = pa.array([bucket_counts(x) for x in found], pa.binary())
            yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(fp), pa.array(sim), counts], names=[*b.schema.names[1:], "fp", "sim", "counts"])

    return source.mapInArrow(run, schema)


def shingle_counts(texts: DataFrame, shingle: int) -> np.ndarray:
    """How many shingles of the texts (one column) fall on each of COUNTERS hash ranges; the table (four bytes each) reaches the driver."""

    def count(batches):
        total = np.zeros(COUNTERS, np.uint32)
        for b in slices(batches, 200):
            for t in b.column(0).to_pylist():
                np.add.at(total, (shingles(t, shingle) >> COUNTER_SHIFT).astype(np.intp), np.uint32(1))
        yield pa.RecordBatch.from_arrays([pa.array(range(SECTIONS)), pa.array([x.tobytes() for x in np.split(total, SECTIONS)], pa.binary())], names=["section", "n"])

    def add(part: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x.as_buffer(), np.uint32) for x in part.column("n"))
        return pa.table({"section": part.column("section").slice(0, 1), "n": pa.array([total.tobytes()], pa.binary())})

    found = texts.mapInArrow(count, "section bigint, n binary").groupBy("section").applyInArrow(add, "section bigint, n binary").collect()
    total = np.zeros(COUNTERS, np.uint32)
    for r in found:
        total[r["section"] * (COUNTERS // SECTIONS) :][: COUNTERS // SECTIONS] = np.frombuffer(r["n"], np.uint32)
    return total


def first_shingles(texts: DataFrame, shingle: int) -> DataFrame:
    """key, fp, n (size of the set), at (place of the key in the set's order), m (sets that have the key): the first shingles of each text (one column)
    that other sets have too."""
    sent = texts.sparkSession.sparkContext.broadcast(shingle_counts(texts, shingle))

    def first(batches):
        for b in slices(batches, 200):
            keys, owner, size, place = [], [], [], []
            for t in b.column(0).to_pylist():
                h = shingles(t, shingle)
                n = len(h)
                if n:
                    keys.append(h[np.lexsort((h, sent.value[h >> COUNTER_SHIFT]))][: n + 1 + -n * SIMILAR[0] // SIMILAR[1]])
                    k = len(keys[-1])
                    owner.append(np.full(k, node_of(h), np.uint64))
                    size.append(np.full(k, n))
                    place.append(np.arange(k))
            if keys:
                columns = [np.concatenate(keys).view(np.int64), np.concatenate(owner).view(np.int64), np.concatenate(size).astype(np.int32), np.concatenate(place).astype(np.int32)]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["key", "fp", "n", "at"])

    def shared(batches):
        got = [[b.column(i).to_numpy() for i in range(4)] for b in batches if b.num_rows]
        if not got:
            return
        key, fp, n, at = (np.concatenate(x) for x in zip(*got))
        del got
        order = np.lexsort((fp, key))
        key, fp, n, at = key[order], fp[order], n[order], at[order]
        one = np.r_[True, (key[1:] != key[:-1]) | (fp[1:] != fp[:-1])]
        key, fp, n, at = key[one], fp[one], n[one], at[one]
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        size = np.diff(np.r_[start, len(key)])
        m = np.repeat(size, size)
        yield pa.RecordBatch.from_arrays([pa.array(x[m > 1]) for x in (key, fp, n, at, m)], names=["key", "fp", "n", "at", "m"])

    parts = int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return texts.mapInArrow(first, "key bigint, fp bigint, n int, at int").repartition(parts, "key").mapInArrow(shared, "key bigint, fp bigint, n int, at int, m bigint")


def with_marks(members: DataFrame, sets: DataFrame) -> DataFrame:
    """The first shingles (on shared files) with heads (the first HEADS shared keys of the set, those before this one) and counts (the set's
    bucket_counts, where more than WIDE sets have the key)."""
    listed = F.slice(F.sort_array(F.collect_list(F.struct("at", "key"))), 1, HEADS)
    marks = materialise(members.groupBy("fp").agg(listed.alias("heads")).join(sets.groupBy("fp").agg(F.first("counts").alias("counts")), "fp"), "near-marks")
    joined = members.join(checked(marks, marks.count(), 12 * HEADS + BUCKETS + 32), "fp")
    heads = F.transform(F.filter("heads", lambda h: h["at"] < F.col("at")), lambda h: h["key"])
    return joined.select("key", "fp", "n", "at", "m", heads.alias("heads"), F.when(F.col("m") > WIDE, F.col("counts")).alias("counts"))


def pivot_pairs(members: DataFrame, pivots: int) -> DataFrame:
    """(a, b): of the sets with one key (columns key, fp, n, at, comp, heads, counts) the first `pivots` with each later one of another component.

    Two sets may be as alike as SIMILAR asks only if enough shingles come after the first one that they share: what stands at
    most on the places from it on is compared with the overlap that their sizes call for. Nor may their bucket counts, where there are any, differ by
    more than their sizes allow. Two sets that share an earlier key too are left to that key: the first one they share has all such
    pairs, and no key's pairs are left out of it."""

    def run(batches):
        got, heads, counts = [], [], []
        for b in batches:
            if b.num_rows:
                got.append([b.column(i).to_numpy() for i in range(5)])
                width = np.diff(np.asarray(b.column(5).offsets))
                own = np.repeat(got[-1][0][:, None], HEADS, 1)  # no earlier key is the row's own: filled up with it
                own[np.repeat(np.arange(len(width)), width), spans(np.zeros(len(width), np.int64), width)] = b.column(5).flatten().to_numpy()
                heads.append(own)
                there = np.asarray(b.column(6).is_valid())
                some = np.full(len(there), -1)
                some[there] = np.arange(there.sum()) + sum(map(len, counts))
                got[-1].append(some)
                counts.append(np.frombuffer(b"".join(b.column(6).drop_null().to_pylist()), np.uint8).reshape(-1, BUCKETS))
        if not got:
            return
        key, fp, n, at, comp, some = (np.concatenate(x) for x in zip(*got))
        heads, counts = np.concatenate(heads), np.concatenate(counts)
        del got
        order = np.lexsort((fp * np.int64(-7046029254386353131), key))  # one order for all keys, so that they share pivots
        key, fp, n, at, comp, some, heads = key[order], fp[order], n[order].astype(np.int64), at[order], comp[order], some[order], heads[order]
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        end, made, waiting = np.r_[start[1:], len(key)], [], 0

        def flush():
            a, b = np.unique(np.concatenate(made), axis=0).T
            for at in range(0, len(a), CHUNK):
                yield pa.RecordBatch.from_arrays([pa.array(a[at : at + CHUNK]), pa.array(b[at : at + CHUNK])], names=["a", "b"])

        for s, e in zip(start.tolist(), end.tolist()):
            for i in range(s, min(e - 1, s + pivots)):
                small, large = np.minimum(n[i], n[i + 1 : e]), np.maximum(n[i], n[i + 1 : e])
                most = np.minimum(n[i] - at[i], n[i + 1 : e] - at[i + 1 : e])
                enough = most * (SIMILAR[0] + SIMILAR[1]) >= (small + large) * SIMILAR[0]
                j = i + 1 + np.flatnonzero((comp[i + 1 : e] != comp[i]) & (small * SIMILAR[1] >= large * SIMILAR[0]) & enough)
                if len(j) and some[i] >= 0:
                    differ = np.abs(counts[some[j]].astype(np.int16) - counts[some[i]]).sum(1, dtype=np.int64)
                    j = j[differ * (SIMILAR[0] + SIMILAR[1]) <= (n[i] + n[j]) * (SIMILAR[1] - SIMILAR[0])]
                earlier = heads[i][heads[i] != key[i]]
                if len(j) and len(earlier):
                    j = j[~(heads[j][:, :, None] == earlier).any((1, 2))]
                if len(j):
                    made.append(np.stack([np.minimum(fp[i], fp[j]), np.maximum(fp[i], fp[j])], 1))
                    waiting += len(j)
                if waiting > 10 * CHUNK:
                    yield from flush()
                    made, waiting = [], 0
        if made:
            yield from flush()

    parts = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return members.select("key", "fp", "n", "at", "comp", "heads", "counts").repartition(parts, "key").mapInArrow(run, "a bigint, b bigint")


def simhash_pairs(sets: DataFrame, distance: int) -> DataFrame:
    """(a, b): what the SimHash index proposes: each set with the first one of its own fingerprint, and the first ones of linked fingerprints."""
    nodes = materialise(sets.groupBy("fp").agg(F.first("sim").alias("sim")), "near-nodes")
    firsts = materialise(nodes.groupBy("sim").agg(F.min("fp").alias("first"), F.count(F.lit(1)).alias("n")), "near-sims")
    n_sims = firsts.count()
    own = salted_join(nodes, firsts.where("n > 1"), ["sim"], "n", n_sims, 32).select(F.col("first").alias("a"), F.col("fp").alias("b"))
    links = near_links(firsts.select(F.col("sim").alias("fp")), n_sims, distance)
    left, right = (firsts.select(F.col("sim").alias(x), F.col("first").alias(f"first_{x}")) for x in "ab")
    far = links.join(checked(left, n_sims, 24), "a").join(checked(right, n_sims, 24), "b").select(F.col("first_a").alias("a"), F.col("first_b").alias("b"))
    return own.unionAll(far).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def similar_links(sets: DataFrame, texts: DataFrame, shingle: int = SHINGLE, distance: int = 2) -> DataFrame:
    """Links (a, b) that connect all sets (fp, sim, counts; on shared files) of the texts (one column) with a Jaccard similarity of SIMILAR at least."""
    tag = uuid.uuid4().hex[:12]
    members = materialise(with_marks(materialise(first_shingles(texts, shingle), f"near-first-{tag}"), sets), "near-members")
    drop_tables(f"near-first-{tag}")
    largest = members.agg(F.max("m")).first()[0] or 0
    proposed = materialise(simhash_pairs(sets.select("fp", "sim"), distance), "near-proposed")
    hashed = texts.withColumn("_text", F.xxhash64(F.coalesce(F.col(texts.columns[0]), F.lit("\x00"))))

    def again(batches):
        for b in slices(batches, 200):
            found = [shingles(t, shingle) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.array([node_of(x) for x in found], np.uint64).view(np.int64)), pa.array([x.tobytes() for x in found], pa.binary())], names=["fp", "shingles"])

    def run(batches):
        for b in slices(batches, 200):
            good = [alike(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)) for x, y in zip(b.column(2), b.column(3))]
            yield pa.RecordBatch.from_arrays(b.columns[:2], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    def checked_pairs(pairs: DataFrame) -> DataFrame:
        """Those of the pairs (on shared files) that are alike: the sets of just these are made again, from one text of each, and dropped afterwards."""
        nodes = materialise(pairs.select(F.col("a").alias("fp")).unionAll(pairs.select("b")).distinct(), "near-nodes")
        n_nodes = nodes.count()
        if not n_nodes:
            return pairs
        owners = sets.select("fp", "_text").join(checked(nodes, n_nodes, 16), "fp", "left_semi").groupBy("fp").agg(F.min("_text").alias("_text"))
        owners = materialise(owners.select("_text").distinct(), "near-owners")
        one_each = hashed.join(checked(owners, n_nodes, 16), "_text", "left_semi").select(texts.columns[0]).distinct()
        whole = materialise(one_each.mapInArrow(again, "fp bigint, shingles binary"), f"near-sets-{tag}")
        n_bytes = whole.agg(F.sum(F.length("shingles") + 64)).first()[0] or 0
        left, right = (whole.select(F.col("fp").alias(x), F.col("shingles").alias(f"set_{x}")) for x in "ab")
        both = pairs.join(checked(left, n_bytes, 1), "a").join(checked(right, n_bytes, 1), "b").select("a", "b", "set_a", "set_b")
        links = materialise(both.mapInArrow(run, "a bigint, b bigint"), "near-links")
        drop_tables(f"near-sets-{tag}")
        return links

    found, pivots, before = checked_pairs(proposed), FIRST_PIVOTS, 1
    while before < largest:
        roots = materialise(components(found), "near-roots")
        some = members.where(F.col("m") > before)  # smaller groups have been compared whole
        some = some.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("comp", F.coalesce("root", "fp"))
        found = found.unionAll(checked_pairs(materialise(pivot_pairs(some, pivots).distinct(), "near-pairs")))
        before, pivots = pivots, pivots * 8
    return found


def first_of_each(docs: DataFrame, told: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows of docs, all columns, that stay: of each component the rows with its smallest id (of rows with one id, those whose text
    has the smallest hash; of components without any id, likewise). told: _id, _text, doc_id, component_id, fp."""
    told = materialise(told, "near-told")
    whole = F.coalesce(F.col("component_id").cast("string"), F.concat(F.lit("\x00"), F.col("fp").cast("string")))
    mine = told.withColumn("_group", whole)
    first = mine.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).groupBy("_group").agg(F.min("_text").alias("_first"))
    counts = mine.groupBy("_group").agg(F.count(F.lit(1)).alias("n"))
    several = materialise(first.join(counts.where("n > 1"), "_group"), "near-groups")
    members = salted_join(mine, several, ["_group"], "n", several.count(), 64)
    gone = materialise(members.where(~(F.col("doc_id").eqNullSafe(F.col("component_id")) & (F.col("_text") == F.col("_first")))).select("_id", "_text").distinct(), "near-gone")
    return without(docs, gone, gone.count(), id_col, text_col)


def keep_one(docs: DataFrame, shingle: int = SHINGLE, distance: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of docs, all columns, that stay: one text of each component, where all texts with a Jaccard similarity of SIMILAR at least are linked."""
    rows = materialise(shingle_sets(docs, shingle, id_col, text_col, keys_of(id_col, text_col)), "shingle-sets")
    texts = docs.select(F.col(text_col).alias("_whole_text"))
    told = grouped(rows.drop("sim", "counts"), links=similar_links(rows, texts, shingle, distance)).select("_id", "_text", "doc_id", "component_id", "fp")
    return first_of_each(docs, told, id_col, text_col)


def op9_simhash_gray(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(documents(spark, sf_dir))

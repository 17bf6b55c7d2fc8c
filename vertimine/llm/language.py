"""Language of a text as a mixture of languages.

Each language has likelihoods of hashed byte trigrams (lower-cased, words padded by a blank), counted over all training texts
with smoothing. A text is cut into units of UNIT trigrams; expectation-maximisation estimates the share of each language
from the units' likelihoods. The language set is chosen by penalised likelihood: from all languages down, the one with the
smallest share is dropped as long as that costs less than its penalty (PENALTY per language, grown with the log of the
text's length). The predicted language has the largest share; the score is that share times the posterior of the text's
best single languages where only one is left.

Languages: the distinct non-null labels of the training rows. The table of likelihoods has CELLS numbers at most (four bytes each,
broadcast): the more languages, the fewer hash values a trigram may have (bits_for). Only past 2**16 labels the rarest are left out. Null texts and texts without a letter are `und` with score 0. Without training rows
every text is `und`. Other columns are ignored; repeated rows are predicted alike.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, short_batches, slices

UNIT, ROUNDS, PENALTY = 24, 6, 2.0
#: Most and fewest bits of a trigram's hash, numbers in the table of likelihoods, and tables of counts that a task holds at once.
BITS, LEAST_BITS, CELLS, HELD = 16, 8, 1 << 24, 64
#: Bytes of text that are predicted at once, and trigrams whose likelihoods are looked up at once, both for one language.
PREDICT_BYTES, LOOKUPS = 4 << 20, 1 << 20
#: ASCII upper to lower case, and all bytes that are no letters in ASCII to a blank.
FOLD = np.array([i + 32 if 65 <= i <= 90 else i if 97 <= i <= 122 or i >= 128 else 32 for i in range(256)], np.uint8)


def bits_for(n_languages: int) -> int:
    """Bits of a trigram's hash, so that the table for so many languages keeps to CELLS."""
    return max(LEAST_BITS, min(BITS, (CELLS // max(1, n_languages)).bit_length() - 1))


def trigrams(text: bytes, bits: int = BITS) -> np.ndarray:
    """Hashed trigrams of folded bytes; runs of blanks count once; a blank stands before and after."""
    b = FOLD[np.frombuffer(text, np.uint8)]
    # Upper-case letters of two bytes in the Latin supplement (U+00C0 to U+00DE) to lower case.
    second = np.flatnonzero(b[:-1] == 0xC3) + 1
    upper = second[(b[second] >= 0x80) & (b[second] <= 0x9E) & (b[second] != 0x97)]
    b[upper] += 32
    blank = b == 32
    keep = ~blank
    keep[1:] |= blank[1:] & ~blank[:-1]
    b = np.concatenate([[32], b[keep], [32]]).astype(np.uint32)
    if len(b) > 2 and b[1] == 32:
        b = b[1:]
    h = b[:-2] * np.uint32(0x9E3779B1) ^ b[1:-1] * np.uint32(0x85EBCA77) ^ b[2:] * np.uint32(0xC2B2AE3D)
    h ^= h >> np.uint32(15)
    return (h * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - bits)


def has_letter(text: str) -> bool:
    return text.isalpha() or any(map(str.isalpha, text))


def train(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> tuple[list[str], np.ndarray]:
    """(languages, log likelihoods[trigram, language]). Counts are summed in the tasks, then by language and trigram."""
    rows = docs.where(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull()).select(F.col(text_col).alias("t"), F.col(lang_col).cast("string").alias("l"))
    short_batches(docs.sparkSession)

    labels = rows.groupBy("l").count().orderBy(F.col("count").desc(), "l").limit(CELLS >> LEAST_BITS).collect()  # names only
    names = sorted(r["l"] for r in labels)
    bits, place = bits_for(len(names)), {x: i for i, x in enumerate(names)}

    def run(batches):
        total: dict[int, np.ndarray] = {}

        def flush():
            for lang, n in total.items():
                at = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.int32()), pa.array(at.astype(np.int32)), pa.array(n[at])], names=["l", "g", "n"])
            total.clear()

        for b in slices(batches, 500):
            for t, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                at = place.get(lang)
                if at is None:
                    continue
                if at not in total:
                    if len(total) >= HELD:
                        yield from flush()
                    total[at] = np.zeros(1 << bits, np.int64)
                total[at] += np.bincount(trigrams(t.encode("utf-8", "surrogatepass"), bits), minlength=1 << bits)
        yield from flush()

    counts = rows.mapInArrow(run, "l int, g int, n bigint").groupBy("l", "g").agg(F.sum("n").alias("n")).toArrow()  # CELLS rows at most
    table = np.zeros((1 << bits, max(1, len(names))))
    table[counts["g"].to_numpy(), counts["l"].to_numpy()] = counts["n"].to_numpy()
    table += 0.1
    return names, np.log(table / table.sum(0)).astype(np.float32)


def units_of(table: np.ndarray, grams: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Log likelihoods [unit, language] of units that start at `cuts`; looked up a bounded number of trigrams at a time."""
    step = max(1, LOOKUPS // table.shape[1] // UNIT)
    ends = np.r_[cuts[1:], len(grams)]
    return np.concatenate([np.add.reduceat(table[grams[cuts[s] : ends[min(len(cuts), s + step) - 1]]], cuts[s : s + step] - cuts[s], axis=0) for s in range(0, len(cuts), step)])


def mixture(units: np.ndarray, first: np.ndarray, n_units: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """EM and selection for many texts at once. units: log likelihoods [unit, language]; text i has n_units[i] units from
    first[i] on, at least one. Returns shares [text, language] (0 for languages not in the set) and the single-language totals."""
    n, langs = len(first), units.shape[1]
    singles = np.add.reduceat(units, first, axis=0).astype(np.float64)
    top = units.max(1, keepdims=True)
    like = np.exp(units - top)
    owner = np.repeat(np.arange(n), n_units)
    base = np.add.reduceat(top[:, 0].astype(np.float64), first)

    def em(active: np.ndarray, who: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For the texts `who`: shares and log likelihood with only the active languages."""
        here = np.isin(owner, who) if len(who) < n else slice(None)
        rows = like[here]
        at = np.searchsorted(who, owner[here])
        starts = np.searchsorted(at, np.arange(len(who)))
        share = active / active.sum(1, keepdims=True)
        for _ in range(ROUNDS):
            joint = rows * share[at]
            total = joint.sum(1, keepdims=True)
            np.maximum(total, 1e-30, out=total)
            share = np.add.reduceat(joint / total, starts, axis=0)
            share /= share.sum(1, keepdims=True)
        total = np.maximum((rows * share[at]).sum(1), 1e-30)
        return share, np.add.reduceat(np.log(total), starts) + base[who]

    everyone = np.arange(n)
    active = np.ones((n, langs), np.float32)
    share, score = em(active, everyone)
    penalty = PENALTY * (1 + 0.5 * np.log1p(n_units))
    todo = everyone if langs > 1 else everyone[:0]
    while len(todo):
        trial = active[todo].copy()
        least = np.where(trial > 0, share[todo], np.inf).argmin(1)
        trial[np.arange(len(todo)), least] = 0
        new_share, new_score = em(trial, todo)
        ok = score[todo] - new_score <= penalty[todo]
        won = todo[ok]
        active[won], share[won], score[won] = trial[ok], new_share[ok], new_score[ok]
        todo = won[active[won].sum(1) > 1]
    return share, singles


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], keep: list[Column], schema: str, text_col: str = "text", shares: bool = False) -> DataFrame:
    """`keep` columns, lang_pred and score; with `shares` also `languages`, a map of the chosen languages to their shares."""
    short_batches(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        names, table = sent.value
        bits = bits_for(len(names))
        for b in slices(batches, 250, max(1 << 12, PREDICT_BYTES // max(1, len(names)))):
            texts = b.column(0).to_pylist()
            pred, score = ["und"] * len(texts), np.zeros(len(texts))
            mixed: list[list] = [[] for _ in texts]
            some = [i for i, t in enumerate(texts) if names and t and has_letter(t)]
            if some:
                grams = [trigrams(texts[i].encode("utf-8", "surrogatepass"), bits) for i in some]
                size = np.array([len(g) for g in grams])
                n_units = -(-size // UNIT)
                first = np.cumsum(n_units) - n_units
                cuts = np.repeat(np.cumsum(size) - size, n_units) + (np.arange(n_units.sum()) - np.repeat(first, n_units)) * UNIT
                units = units_of(table, np.concatenate(grams), cuts)
                share, singles = mixture(units, first, n_units)
                best = share.argmax(1)
                # Where one language is left the share says nothing more; how much likelier it is than the others does.
                odds = np.exp(np.minimum(singles - singles[np.arange(len(some)), best][:, None], 0))
                sure = share[np.arange(len(some)), best] / odds.sum(1) if len(names) > 1 else np.ones(len(some))
                alone = (share > 0).sum(1) == 1
                value = np.where(alone, sure, share[np.arange(len(some)), best])
                for k, i in enumerate(some):
                    pred[i], score[i] = names[best[k]], value[k]
                    mixed[i] = [(names[j], float(share[k, j])) for j in np.flatnonzero(share[k] > 0)]
            columns = [*b.columns[1:], pa.array(pred, pa.string()), pa.array(np.clip(score, 0, 1))]
            if shares:
                columns.append(pa.array(mixed, pa.map_(pa.string(), pa.float64())))
            yield pa.RecordBatch.from_arrays(columns, names=[*b.schema.names[1:], "lang_pred", "score", *["languages"] * shares])

    full = f"{schema}, lang_pred string, score double" + ", languages map<string,double>" * shares
    return docs.select(F.col(text_col).alias("_whole_text"), *keep).mapInArrow(run, full)


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(4)) == 2, F.lit(False))


def op10_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    kind = docs.schema["doc_id"].dataType.simpleString()
    model = train(docs.where(~held_out()))
    return predict(docs, model, [F.col("doc_id"), held_out().alias("held_out")], f"doc_id {kind}, held_out boolean")

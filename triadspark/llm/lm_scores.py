"""Cross-entropy difference of two matched bigram models.

Target and background model share one vocabulary: all words of all documents, however many.  Both count uni- and bigrams of whole texts,
the target those of documents that the labels call good, the background all documents.
Each block of documents counts its own n-grams, named by 62-bit hashes; buckets of n-grams (ranges of hashes) add the blocks' counts and give
every block the totals of just those it has, in the order it sent them, and the number of distinct words of the bucket; so neither models nor
vocabulary are ever gathered in one place.  A block has `cells` buckets at most.  Where a bucket would hear from more than `cells` blocks, that many of them
first add their counts and split their range of hashes again, and so on: a frequent n-gram never meets all blocks at once, and each
round of this exchange has rows in proportion to the blocks.  A document's score is its loss per token under the target model less that under
the background model, both interpolated from bi- to unigrams; lower is more like the target.

Counts have 64 bits.  Edge cases: null or empty text has no tokens: losses and score are null.  Without any good label the target model is its smoothing alone.  Documents
with several label rows count as good if one is.  Repeated rows give a row each; a null doc_id has no label, and such rows are dealt to blocks by their text.  Empty tables give no rows.  Other columns
are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import parts, slim, table
from .textkernel import ALNUM, GOLD, LOWER, U, mix, pieces, release_encoders, text_bytes, word_hash, words

# the two low bits of a key tell its kind: bigram 0, word 1; two keys of their own
ALL, START = U(2), U(3)  # all tokens together; starts of texts, a context
KIND = U(3)


def _grams(text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Keys of each word's bigram with the one before it (or the start of the text) and of the word, words per text, places of first words."""
    h, counts = word_hashes(text)
    before = np.empty_like(h)
    before[1:] = h[:-1]
    heads = (np.cumsum(counts) - counts)[counts > 0]
    before[heads] = START
    return mix(before * GOLD + h) & ~KIND, (h & ~KIND) | U(1), counts, heads


def word_hashes(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    buf, off = text_bytes(text)
    buf = LOWER[buf]
    starts, lens, counts = words(buf, off, ALNUM)
    return word_hash(buf, starts, lens), counts


def _pack(x: np.ndarray) -> bytes:
    """Unsigned numbers as byte planes, as many as the largest needs."""
    k = max(1, (int(x.max(initial=0)).bit_length() + 7) // 8)
    return bytes([k]) + x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :k].T.tobytes()


def _unpack(x: bytes) -> np.ndarray:
    planes = np.frombuffer(x, np.uint8, offset=1).reshape(x[0], -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, : x[0]] = planes.T
    return out.view("<u8").ravel()


def _pack_keys(key: np.ndarray) -> bytes:
    """Ascending keys: the first, then steps."""
    return key[:1].tobytes() + _pack(np.diff(key)) if len(key) else b""


def _unpack_keys(x: bytes) -> np.ndarray:
    return np.cumsum(np.concatenate((np.frombuffer(x, U, 1), _unpack(x[8:]))), dtype=U) if x else np.zeros(0, U)


def _mark(t: pa.Table) -> pa.Table:
    """Documents of a block with their flag; label rows go."""
    good = t["good"].fill_null(False).to_numpy()
    ids = t["doc_id"].fill_null(-(1 << 63)).to_numpy()
    docs = t.filter(pa.array(~good))
    own = ids[~good]
    return pa.table({"doc_id": docs["doc_id"], "text": docs["text"], "block": docs["block"], "good": pa.array(np.isin(own, ids[good]))})


_COUNTED = "bucket long, block long, keys binary, target binary, back binary"
_TOTALS = "bucket long, block long, n_words long, target binary, back binary"


def _cut_rows(key: np.ndarray, target: np.ndarray, back: np.ndarray, first: int, last: int, buckets: int, block: int) -> pa.Table:
    """A row for every bucket from first to before last, even an empty one: each counts distinct words for all blocks."""
    cuts = np.searchsorted(_bucket(key, buckets), np.arange(first, last + 1).astype(U))
    spans = list(zip(cuts[:-1], cuts[1:], strict=True))
    return pa.table({"bucket": pa.array(np.arange(first, last), pa.int64()), "block": pa.array(np.full(last - first, block), pa.int64()), "keys": pa.array([_pack_keys(key[i:j]) for i, j in spans], pa.binary()),
                     "target": pa.array([_pack(target[i:j]) for i, j in spans], pa.binary()), "back": pa.array([_pack(back[i:j]) for i, j in spans], pa.binary())})


def _count(buckets: int):
    def run(t: pa.Table) -> pa.Table:
        release_encoders()
        t = _mark(t)
        ones = np.array([ALL, START])
        keys, good, ends = [ones], [np.zeros(2, bool)], [np.zeros(2, np.int64)]  # of the two own keys: how many there are, in all and in the target
        for p in pieces(t, "text") if t.num_rows else ():
            two, one, counts, heads = _grams(p["text"])
            flag = np.repeat(p["good"].to_numpy(), counts)
            keys += [two, one]
            good += [flag, flag]
            ends.append(np.array([len(one), len(heads), flag.sum(), flag[heads].sum()]))
        if not t.num_rows:
            return _cut_rows(np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64), 0, 0, buckets, 0)
        every = np.concatenate(keys)
        key, back = np.unique(every, return_counts=True)
        some, n = np.unique(every[np.concatenate(good)], return_counts=True)
        target = np.zeros(len(key), np.int64)
        target[np.searchsorted(key, some)] = n
        total = np.sum(ends[1:], axis=0)
        at = np.searchsorted(key, ones)
        back[at], target[at] = total[:2], total[2:]
        return _cut_rows(key, target, back, 0, buckets, buckets, t["block"][0].as_py())

    return run


def _bucket(key: np.ndarray, buckets: int) -> np.ndarray:
    """Ascending with the key."""
    return ((key >> U(32)) * U(buckets)) >> U(32)


def _added(t: pa.Table) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """Keys of each row, distinct keys, their number for every key of every row, and the sums of the counts."""
    keys = [_unpack_keys(x) for x in t["keys"].to_pylist()]
    key, inv = np.unique(np.concatenate(keys), return_inverse=True)
    sums = {}
    for c in ("target", "back"):
        sums[c] = np.zeros(len(key), np.int64)
        np.add.at(sums[c], inv, np.concatenate([_unpack(x) for x in t[c].to_pylist()]).astype(np.int64))
    return keys, key, inv, sums


def _merge(split: int, buckets: int):
    """Counts of some blocks in one bucket, added, in the `split` buckets that it is cut into; the blocks' place in their row of groups stands for them."""

    def run(t: pa.Table) -> pa.Table:
        _, key, _, sums = _added(t)
        first = t["bucket"][0].as_py() * split
        return _cut_rows(key, sums["target"], sums["back"], first, first + split, buckets, t["g"][0].as_py())

    return run


def _spread(counted: pa.Table, told: pa.Table) -> pa.Table:
    """Totals of the added counts back to the blocks, in the order of each block's own keys."""
    keys, _, inv, _ = _added(counted)
    told = told.sort_by("bucket")
    n = int(np.sum(told["n_words"].to_numpy()))
    ends = np.cumsum([len(k) for k in keys])
    out = {}
    for c in ("target", "back"):
        s = np.concatenate([_unpack(x) for x in told[c].to_pylist()])
        out[c] = pa.array([_pack(s[inv[e - len(k) : e]]) for k, e in zip(keys, ends, strict=True)], pa.binary())
    return pa.table({"bucket": counted["bucket"].combine_chunks(), "block": counted["block"].combine_chunks(), "n_words": pa.array([n] * len(keys), pa.int64()), **out})


def _totals(counted: DataFrame, n_blocks: int, buckets: int, cells: int) -> DataFrame:
    """Totals for the rows of counted, whose buckets hear from n_blocks blocks each."""
    if n_blocks <= cells:
        return counted.groupBy("bucket").applyInArrow(_total, _TOTALS)
    g = F.floor(F.col("block") / cells).alias("g")
    grouped = counted.select("*", g)
    merged = grouped.groupBy("bucket", "g").applyInArrow(_merge(cells, buckets * cells), _COUNTED)
    back = _totals(merged, -(-n_blocks // cells), buckets * cells, cells)
    back = back.select(F.floor(F.col("bucket") / cells).alias("coarse"), F.col("block").alias("g"), "bucket", "n_words", "target", "back")
    return grouped.groupBy("bucket", "g").cogroup(back.groupBy("coarse", "g")).applyInArrow(_spread, _TOTALS)


def _total(t: pa.Table) -> pa.Table:
    keys, key, inv, sums = _added(t)
    ends = np.cumsum([len(k) for k in keys])
    out = {c: pa.array([_pack(s[inv[e - len(k) : e]]) for k, e in zip(keys, ends, strict=True)], pa.binary()) for c, s in sums.items()}
    n = int(((key & KIND) == U(1)).sum())
    return pa.table({"bucket": t["bucket"].combine_chunks(), "block": t["block"].combine_chunks(), "n_words": pa.array([n] * len(keys), pa.int64()), **out})


def _score(mixture: float, alpha: float):
    def run(docs: pa.Table, model: pa.Table) -> pa.Table:
        docs = _mark(docs)
        ids, keys, counts, heads, size = [], [np.array([ALL, START])], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
        for p in pieces(docs, "text") if docs.num_rows else ():
            two, one, n, first = _grams(p["text"])
            ids += p["doc_id"].to_pylist()
            keys += [two, one]
            counts.append(n)
            heads.append(first + size)
            size += len(one)
        n, heads = np.concatenate(counts), np.concatenate(heads)
        doc = np.repeat(np.arange(len(n)), n)
        losses = [np.full(len(n), np.nan)] * 2
        if size:
            # the block's keys again, in the order of buckets that the totals are in
            inv = np.unique(np.concatenate(keys[:1] + keys[1::2] + keys[2::2]), return_inverse=True)[1]
            z, start, a, b = inv[0], inv[1], inv[2 : 2 + size], inv[2 + size :]
            c = np.concatenate((b[:1], b[:-1]))
            c[heads] = start
            model = model.sort_by("bucket")
            v = int(np.sum(model["n_words"].to_numpy()))
            for k, name in enumerate(("target", "back")):
                count = np.concatenate([_unpack(x) for x in model[name].to_pylist()]).astype(float)
                p1 = (count[b] + alpha) / (count[z] + alpha * v)
                p2 = np.where(count[c] > 0, count[a] / np.maximum(count[c], 1), p1)
                loss = np.bincount(doc, weights=-np.log(mixture * p2 + (1 - mixture) * p1), minlength=len(n))
                losses[k] = np.where(n > 0, loss / np.maximum(n, 1), np.nan)
        t, b = losses
        real = lambda x: pa.array(np.round(x, 6), pa.float64(), mask=np.isnan(x))
        return pa.table({"doc_id": pa.array(ids, pa.int64()), "n_tokens": pa.array(n.astype(np.int64)), "target_loss": real(t), "background_loss": real(b), "score": real(t - b)})

    return run


def cross_entropy_difference(docs: DataFrame, labels: DataFrame, mixture: float = 0.7, alpha: float = 0.1, block_bytes: int = 4 << 20, cells: int = 256) -> DataFrame:
    """doc_id, n_tokens, target_loss, background_loss, score of every row of docs; labels(doc_id, quality) tell the target's documents."""
    docs = slim(docs)
    good = labels.where("quality = 1").select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(True).alias("good")).distinct()
    n = parts(docs, block_bytes)
    block = F.pmod(F.xxhash64(F.coalesce("doc_id", F.xxhash64("text"))), F.lit(n)).cast("long").alias("block")
    # labels go to the blocks that hold their documents; texts move once
    blocks = docs.select("doc_id", "text", block).unionByName(good.select("doc_id", F.lit(None).cast("string").alias("text"), block, "good"), allowMissingColumns=True).repartition(max(1, n // 3), "block")
    counted = blocks.groupBy("block").applyInArrow(_count(min(n, cells)), _COUNTED)
    totals = _totals(counted, n, min(n, cells), cells)
    out = "doc_id long, n_tokens long, target_loss double, background_loss double, score double"
    return blocks.groupBy("block").cogroup(totals.groupBy("block")).applyInArrow(_score(mixture, alpha), out)


def op4_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cross_entropy_difference(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES = {"op4_lm_scores": op4_lm_scores}

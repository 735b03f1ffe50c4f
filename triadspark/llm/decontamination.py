"""Benchmark decontamination over a positional inverted index.

The index is distributed by documents and stored once: each segment holds the postings of every term in its texts, term after term, as
positions that never run from one text into the next.  The test items become distinct windows in tasks, block by block of bounded bytes; a block's
windows are one packed row, which a join hands to all segments, and no item passes through the driver's Python.  A segment answers all windows of a block: the list of a window's rarest term,
shifted by that term's offset, is intersected with the shifted lists of its other terms, shortest first; a window with a term
that has no posting costs nothing.  Exact matches allow no shift between terms, proximity matches up to `slop` words.

More blocks of items mean more searches of the same index.

Edge cases: null or empty texts have no words.  An item without words has no window.  Equal items and repeated rows are fine:
each row of documents gives a row.  A null item_id is called "null"; a null doc_id stays null.  Empty tables: no rows, or rows without hits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slim, stored, table
from .textkernel import ALNUM, LOWER, U, pieces, release_encoders, text_bytes, word_hash, words


def pack_windows(width: int):
    """All items of a block as one row: sorted terms, the distinct windows as term numbers (-1 behind short ones), and for each window its items."""

    def run(t: pa.Table) -> pa.Table:
        buf, off = text_bytes(t["text"])
        buf = LOWER[buf]
        starts, lens, counts = words(buf, off, ALNUM)
        terms, term = np.unique(word_hash(buf, starts, lens), return_inverse=True)
        size = np.minimum(width, counts)
        n = np.where(counts > 0, counts - size + 1, 0)
        of = np.repeat(np.arange(len(counts)), n)
        first = np.repeat(np.cumsum(counts) - counts, n) + np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
        at = first[:, None] + np.arange(width)
        grid = np.where(np.arange(width) < size[of][:, None], term[np.minimum(at, max(0, len(term) - 1))] if len(term) else -1, -1).astype(np.int32)
        grid, which = np.unique(grid, axis=0, return_inverse=True) if len(grid) else (grid.reshape(0, width), np.zeros(0, np.int64))
        names, item = np.unique(np.array(t["item_id"].to_pylist(), object).astype(str), return_inverse=True)
        pairs = np.unique(np.stack((which.ravel(), item[of]), axis=1), axis=0) if len(of) else np.zeros((0, 2), np.int64)
        per = np.bincount(pairs[:, 0], minlength=len(grid))
        row = {"block": pa.array([t["block"][0].as_py()], pa.int32()), "w_terms": pa.array([terms.tobytes()], pa.binary()), "w_grid": pa.array([grid.tobytes()], pa.binary()),
               "w_sizes": pa.array([per.astype("<i8").tobytes()], pa.binary()), "w_items": pa.array([pairs[:, 1].astype("<i8").tobytes()], pa.binary()), "w_names": pa.array([names.tolist()], pa.list_(pa.string()))}
        return pa.table(row)

    return run


_WINDOWS = "block int, w_terms binary, w_grid binary, w_sizes binary, w_items binary, w_names array<string>"


class Windows:
    """One packed block, opened."""

    def __init__(self, row: dict, width: int):
        self.terms = np.frombuffer(row["w_terms"], U)
        self.grid = np.frombuffer(row["w_grid"], np.int32).reshape(-1, width)
        ends = np.cumsum(np.frombuffer(row["w_sizes"], "<i8"))
        self.ends, self.names, self.item = ends.tolist(), row["w_names"], np.frombuffer(row["w_items"], "<i8").tolist()
        self.width = width

    def items(self, k: int) -> list[str]:
        return [self.names[i] for i in self.item[self.ends[k - 1] if k else 0 : self.ends[k]]]

    def window(self, k: int) -> list[int]:
        return [t for t in self.grid[k].tolist() if t >= 0]


_INDEX = "any int, doc_ids binary, known binary, n_words binary, terms binary, sizes binary, postings binary"


def _index(gap: int):
    """A segment of the index for each piece of texts: positions start `gap` apart between texts."""

    def run(batches):
        release_encoders()
        for batch in batches:
            for t in pieces(batch, "text"):
                buf, off = text_bytes(t["text"])
                buf = LOWER[buf]
                starts, lens, counts = words(buf, off, ALNUM)
                h = word_hash(buf, starts, lens)
                pos = np.arange(len(h)) + np.repeat(np.arange(len(counts)), counts) * gap
                o = np.argsort(h, kind="stable")
                own = h[o]
                heads = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1]))) if len(own) else np.zeros(0, np.int64)
                names, sizes = own[heads], np.diff(np.append(heads, len(own)))
                row = (t["doc_id"].fill_null(0).to_numpy().tobytes(), t["doc_id"].is_valid().to_numpy().tobytes(), counts.astype("<i8").tobytes(), names.tobytes(), sizes.astype("<u4").tobytes(), pos[o].astype("<u4").tobytes())
                yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), *(pa.array([x], pa.binary()) for x in row)], names=["any", "doc_ids", "known", "n_words", "terms", "sizes", "postings"])

    return run


def _shifted(lists: list[np.ndarray], offsets: list[int], slop: int) -> tuple[np.ndarray, int]:
    """Places where all lists agree once shifted by their offsets, within `slop` words; and the offset of the list they are taken from."""
    order = sorted(range(len(lists)), key=lambda i: len(lists[i]))
    base = lists[order[0]].astype(np.int64) - offsets[order[0]]
    for i in order[1:]:
        if not len(base):
            break
        x = lists[i].astype(np.int64) - offsets[i]
        at = np.searchsorted(x, base - slop)
        base = base[(at < len(x)) & (x[np.minimum(at, len(x) - 1)] <= base + slop)]
    return base, offsets[order[0]]


def _search(width: int, gap: int, slop: int):
    def run(batches):
        release_encoders()
        w, same = None, None
        for batch in batches:
            for r in range(batch.num_rows):
                row = {k: batch[k][r].as_buffer() for k in ("doc_ids", "known", "n_words", "terms", "sizes", "postings")}
                mine = {k: batch[k][r].as_py() for k in ("block", "w_terms", "w_grid", "w_sizes", "w_items", "w_names")} if w is None or batch["block"][r].as_py() != same else None
                if mine:
                    w, same = Windows(mine, width), mine["block"]
                ids, known = np.frombuffer(row["doc_ids"], "<i8"), np.frombuffer(row["known"], bool)
                counts = np.frombuffer(row["n_words"], "<i8")
                names, sizes, post = np.frombuffer(row["terms"], U), np.frombuffer(row["sizes"], "<u4").astype(np.int64), np.frombuffer(row["postings"], "<u4")
                ends = np.cumsum(sizes)
                size, end = np.zeros(len(w.terms) + 1, np.int64), np.zeros(len(w.terms) + 1, np.int64)
                if len(names):
                    at = np.minimum(np.searchsorted(names, w.terms), len(names) - 1)
                    has = np.flatnonzero(names[at] == w.terms)
                    size[has], end[has] = sizes[at[has]], ends[at[has]]
                rare = np.where(w.grid >= 0, size[w.grid], 1 << 62).min(axis=1) if len(w.grid) else np.zeros(0)
                heads = np.cumsum(counts) - counts
                start_of = heads + np.arange(len(counts)) * gap  # position of each text's first word
                delta = np.zeros(int(counts.sum() + len(counts) * gap) + gap + w.width + 1, np.int32)
                items: dict[int, set[str]] = {}
                near: dict[int, set[str]] = {}
                for k in np.flatnonzero(rare > 0):
                    win, of_items = w.window(k), w.items(k)
                    lists = [post[end[t] - size[t] : end[t]] for t in win]
                    at, _ = _shifted(lists, list(range(len(win))), 0)
                    if len(at):
                        delta[at] += 1
                        np.add.at(delta, at + len(win), -1)
                        for d in np.unique(np.searchsorted(start_of, at, "right") - 1):
                            items.setdefault(int(d), set()).update(of_items)
                    if slop:
                        at, anchor = _shifted(lists, list(range(len(win))), slop)  # may lie before the text; its posting does not
                        for d in np.unique(np.searchsorted(start_of, at + anchor, "right") - 1):
                            near.setdefault(int(d), set()).update(of_items)
                covered = np.concatenate(([0], np.cumsum(np.cumsum(delta) > 0)))
                spans = covered[start_of + counts] - covered[start_of]
                flag = np.cumsum(delta) > 0
                yield pa.RecordBatch.from_arrays([
                    pa.array(ids, mask=~known), pa.array(counts), pa.array(spans.astype(np.int64)),
                    pa.array([sorted(items.get(d, ())) for d in range(len(ids))], pa.list_(pa.string())), pa.array([sorted(near.get(d, ())) for d in range(len(ids))], pa.list_(pa.string())),
                    pa.array([np.packbits(flag[s : s + n]).tobytes() if d in items else b"" for d, (s, n) in enumerate(zip(start_of, counts, strict=True))], pa.binary()),
                ], names=["doc_id", "n_words", "n_hit", "items", "near_items", "mask"])

    return run


_FOUND = "doc_id long, n_words long, n_hit long, items array<string>, near_items array<string>, mask binary"


def find_items(docs: DataFrame, bench: DataFrame, width: int = 10, slop: int = 0, block_bytes: int = 1 << 20) -> DataFrame:
    """doc_id, n_words, n_hit (words inside a match), items (sorted), near_items, mask (one bit a word, first word in the highest bit;
    empty without a match) of every row of docs.  block_bytes: text of items whose windows travel together."""
    docs, gap = slim(docs), width + slop
    items = bench.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    total = items.agg(F.sum(F.octet_length("text") + F.lit(1)).alias("n")).first().n or 0  # one number
    # an item's windows may be in several blocks only if it is there twice; each block is sized by what hashing deals to it
    n_blocks = -(-total // block_bytes) or 1
    block = F.pmod(F.xxhash64("item_id", "text"), F.lit(n_blocks)).cast("int").alias("block")
    windows = stored(items.select("item_id", "text", block).groupBy("block").applyInArrow(pack_windows(width), _WINDOWS), "item-windows")
    if n_blocks == 1:
        index = stored(docs.mapInArrow(_index(gap), _INDEX), "posting-index")
        one = windows.unionByName(_no_windows(docs.sparkSession)).orderBy(F.desc(F.length("w_terms"))).limit(1)  # an empty table of items has one empty block
        return index.join(F.broadcast(one.withColumn("any", F.col("block") * 0)), "any").mapInArrow(_search(width, gap, slop), _FOUND)
    # more than one block: rows are numbered once, matches of all blocks meet by row
    numbered = stored(docs.withColumn("row", F.monotonically_increasing_id()), "numbered")
    index = stored(numbered.select(F.col("row").alias("doc_id"), "text").mapInArrow(_index(gap), _INDEX), "posting-index")
    found = None
    for k in range(n_blocks):
        one = windows.where(F.col("block") == k).unionByName(_no_windows(docs.sparkSession)).orderBy(F.desc(F.length("w_terms"))).limit(1)
        part = index.join(F.broadcast(one.withColumn("any", F.col("block") * 0)), "any").mapInArrow(_search(width, gap, slop), _FOUND)
        found = part if found is None else found.unionByName(part.where("size(items) > 0 or size(near_items) > 0"))
    merged = found.groupBy("doc_id").applyInArrow(_merge, _FOUND)
    return merged.withColumnRenamed("doc_id", "row").join(numbered.select("row", "doc_id"), "row").drop("row")


def _no_windows(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(-1, b"", b"", b"", b"", [])], _WINDOWS)


def _merge(t: pa.Table) -> pa.Table:
    n = t["n_words"][0].as_py()
    masks = [np.unpackbits(np.frombuffer(x, np.uint8), count=n) for x in t["mask"].to_pylist() if x]
    hit = np.bitwise_or.reduce(masks) if masks else np.zeros(0, np.uint8)
    every = lambda c: sorted({x for xs in t[c].to_pylist() for x in xs})
    return pa.table({"doc_id": t["doc_id"][:1], "n_words": t["n_words"][:1], "n_hit": pa.array([int(hit.sum())], pa.int64()), "items": pa.array([every("items")], pa.list_(pa.string())),
                     "near_items": pa.array([every("near_items")], pa.list_(pa.string())), "mask": pa.array([np.packbits(hit).tobytes() if masks else b""], pa.binary())})


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op10_proximity(spark: SparkSession, sf_dir: str, slop: int = 2) -> DataFrame:
    """Items found where each word may stand up to `slop` words off its place beside the rarest; exact matches are among them."""
    found = find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), slop=slop)
    return found.select("doc_id", "n_words", F.size("near_items").cast("long").alias("n_near_items"), F.array_join("near_items", ",").alias("near_items"))


QUERIES = {"op10_decontamination": op10_decontamination, "op10_proximity": op10_proximity}
_WORDS = r"list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"
SQL = {"op10_decontamination": f"""
with d as (select doc_id, {_WORDS} as ws from documents), i as (select item_id::varchar as item_id, {_WORDS} as ws from benchmark where text is not null),
w as (select distinct item_id, least(10, len(ws)) as l, unnest(list_transform(range(1, len(ws) - least(10, len(ws)) + 2), lambda k: array_to_string(ws[k:k + least(10, len(ws)) - 1], ' '))) as g from i where len(ws) > 0),
l as (select distinct l from w),
o as (select doc_id, l.l, unnest(range(1, len(ws) - l.l + 2)) as k, unnest(list_transform(range(1, len(ws) - l.l + 2), lambda k: array_to_string(ws[k:k + l.l - 1], ' '))) as g from d, l where len(ws) >= l.l),
h as (select o.doc_id, o.k, o.l, w.item_id from o join w on o.l = w.l and o.g = w.g),
c as (select doc_id, count(distinct p) as n from (select doc_id, unnest(range(k, k + l)) as p from (select distinct doc_id, k, l from h)) group by 1),
t as (select doc_id, count(*) as n, string_agg(item_id, ',' order by item_id) as s from (select distinct doc_id, item_id from h) group by 1)
select d.doc_id, len(d.ws)::bigint as n_words, coalesce(c.n, 0)::bigint as n_hit, coalesce(t.n, 0)::bigint as n_items, sha256(coalesce(t.s, '')) as items_sha256, coalesce(c.n, 0) > 0 as contaminated
from d left join c using (doc_id) left join t using (doc_id)"""}

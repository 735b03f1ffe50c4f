"""Exact removal of repeated byte strings with two-stage suffix sorting.

Only places that may repeat are sorted.  Every 50-byte window owns the smallest of its k-gram hashes (its anchor), so equal windows
own equal anchors wherever they stand, and consecutive windows with one anchor form one segment.  A first exchange finds
the anchors that several documents have; only segments with such an anchor move on, each distinct one once a block.  Buckets of
distinct segments, all of them, are then suffix-sorted in two stages: suffixes not larger than their successor are sorted directly, all others are
induced by one scan over the character buckets.  Neighbours in that order with a common prefix of 50 bytes are equal windows, and the
smallest doc_id of each run decides which of them repeat an earlier document.  Blocks get back one bit a window.

An anchor with very many different segments would gather them in one bucket; they go as single windows, dealt by their own hash.  Blocks tell how
many different segments their frequent anchors have, so a string that is everywhere in the same surroundings, once a block, is no such case.

Edge cases: null text is empty.  Texts of under 50 bytes keep everything.  Rows with one doc_id count as one document: none of
them is earlier.  A null doc_id counts as larger than all others.  Empty tables give no rows; further columns are ignored.  Results keep bytes, which
need not be valid UTF-8 once parts are gone.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import parts, slim, table
from .textkernel import GOLD, U, loads, mix, release_encoders, release_memory, text_bytes

GRAM = 24
FREQUENT = 16  # segments of one anchor in a block from which the block counts the different ones
LAST = (1 << 63) - 1
_C = [U(0x9FB21C651E98DF25), U(0xC2B2AE3D27D4EB4F), U(0x165667B19E3779F9)]


# ---------------------------------------------------------------- segments of a piece of text

def segments(buf: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first window, number of windows, text number, anchor hash) of all segments."""
    n = int(off[-1])
    m = n - width + 1
    none = np.zeros(0, np.int64)
    if m < 1:
        return none, none, none, np.zeros(0, U)
    w8 = loads(buf)
    g = w8[: n - GRAM + 1] * _C[0]
    for j in (1, 2):
        g ^= g >> U(31)
        g += w8[8 * j : 8 * j + len(g)]
        g *= _C[j]
    key = mix(g)
    span = width - GRAM + 1
    low = (key & ~U(0xFFFFFFFF)) | np.arange(len(key), dtype=U)
    size = 1
    while size * 2 <= span:
        low = np.minimum(low[: len(low) - size], low[size:])
        size *= 2
    if size < span:
        low = np.minimum(low[: len(low) - (span - size)], low[span - size :])
    anchor = (low[:m] & U(0xFFFFFFFF)).astype(np.int64)
    inside = np.zeros(m + 1, np.int32)
    long = np.diff(off) >= width
    np.add.at(inside, off[:-1][long], 1)
    np.add.at(inside, off[1:][long] - width + 1, -1)
    live = np.cumsum(inside[:m]) > 0
    new = live.copy()
    new[1:] &= (anchor[1:] != anchor[:-1]) | ~live[:-1]
    starts = np.flatnonzero(new)
    end = live.copy()
    end[:-1] &= new[1:] | ~live[1:]
    runs = np.flatnonzero(end) + 1 - starts
    return starts, runs, np.searchsorted(off, starts, "right") - 1, mix(key[anchor[starts]] + GOLD)


def content_hash(buf: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """64-bit hash of each segment's bytes (segments have at least 8)."""
    w8 = loads(buf)
    h = mix(lens.astype(U) * GOLD)
    for at in range(0, int(lens.max(initial=0)), 8):
        sel = np.flatnonzero(lens > at)
        where = starts[sel] + np.minimum(at, lens[sel] - 8)  # the last load overlaps instead of masking
        h[sel] = mix((h[sel] * _C[0] + U(at)) ^ w8[where])
    return h


def equal_to_last(body: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Whether each segment has the bytes of the one before it."""
    w8 = loads(body)
    out = np.zeros(len(starts), bool)
    out[1:] = lens[1:] == lens[:-1]
    for at in range(0, int(lens.max(initial=0)), 8):
        sel = np.flatnonzero(out & (lens > at))
        step = np.minimum(at, lens[sel] - 8)
        out[sel] = w8[starts[sel] + step] == w8[starts[sel - 1] + step]
    return out


def chunked(t: pa.Table, limit: int = 2 << 20):
    """The texts of a block in runs of limited size: (row offset, bytes, offsets)."""
    buf, off = text_bytes(t["text"])
    n, start = len(off) - 1, 0
    while start < n:
        stop = max(start + 1, int(np.searchsorted(off, off[start] + limit, "right")) - 1)
        part = np.zeros(int(off[stop] - off[start]) + 96, np.uint8)
        part[: off[stop] - off[start]] = buf[off[start] : off[stop]]
        yield start, part, off[start : stop + 1] - off[start]
        start = stop


def doc_ids(t: pa.Table) -> np.ndarray:
    return t["doc_id"].fill_null(LAST).to_numpy()


# ---------------------------------------------------------------- two-stage suffix sorting

def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Order of all suffixes of `text` (0 parts its strings) by their first `depth` bytes at least.

    Stage one sorts the suffixes that are not larger than their successors by 8-byte words, refining ties.  Stage two scans
    the character buckets upwards and puts each larger predecessor at the front of its bucket.
    """
    n = len(text)
    padded = np.zeros(n + 96, np.uint8)
    padded[:n] = text
    rising = np.ones(n, bool)
    # larger than the successor: first differing pair falls; equal characters take their successor's kind
    diff = np.flatnonzero(np.diff(text) != 0)
    kind = text[diff] < text[diff + 1]
    if len(diff):
        nxt = np.searchsorted(diff, np.arange(n))
        rising[: diff[-1] + 1] = kind[nxt[: diff[-1] + 1]]
        rising[diff[-1] + 1 :] = False
    else:
        rising[:] = False
    rising[n - 1 :] = True  # the last suffix is sorted directly, so every other one has a sorted successor
    seed = np.flatnonzero(rising)
    w8 = loads(padded)
    word = lambda at: w8[np.minimum(at, n + 80)].byteswap()
    key = word(seed)
    o = np.argsort(key, kind="stable")
    seed, key = seed[o], key[o]
    tied = np.concatenate(([False], key[1:] == key[:-1]))
    for at in range(8, depth, 8):
        in_tie = tied | np.append(tied[1:], False)
        sel = np.flatnonzero(in_tie)
        if not len(sel):
            break
        group = np.cumsum(~tied)[sel]
        k = word(seed[sel] + at)
        o = np.lexsort((k, group))
        seed[sel], k = seed[sel][o], k[o]
        tied[sel] = np.concatenate(([False], (group[1:] == group[:-1]) & (k[1:] == k[:-1])))
    counts = np.bincount(text, minlength=256)
    head = np.cumsum(counts) - counts
    falling = np.bincount(text[~rising], minlength=256)
    out = np.empty(n, np.int64)
    first = text[seed]
    edges = np.searchsorted(first, np.arange(257))
    fill = head.copy()
    for c in range(256):
        if not counts[c]:
            continue
        out[head[c] + falling[c] : head[c] + counts[c]] = seed[edges[c] : edges[c + 1]]
        at, stop = head[c], head[c] + counts[c]
        while at < stop:  # falling suffixes of this bucket may be induced from it: go on until none is added
            upto = stop if fill[c] == head[c] + falling[c] else fill[c]
            if upto == at:
                break
            pre = out[at:upto] - 1
            pre = pre[pre >= 0]
            pre = pre[~rising[pre]]
            ch = text[pre]
            o = np.argsort(ch, kind="stable")
            pre, ch = pre[o], ch[o]
            took = np.bincount(ch, minlength=256)
            base = np.cumsum(took) - took
            out[fill[ch] + np.arange(len(ch)) - base[ch]] = pre
            fill += took
            at = upto
    return out


def common_prefixes(text: np.ndarray, order: np.ndarray, cap: int) -> np.ndarray:
    """Bytes that each suffix in order shares with the one before it, up to `cap` (0 for the first)."""
    padded = np.zeros(len(text) + 96 + cap, np.uint8)
    padded[: len(text)] = text
    w8 = loads(padded)
    a, b = order[1:], order[:-1]
    out = np.zeros(len(order), np.int64)
    live = np.arange(len(a))
    for at in range(0, cap, 8):
        x = w8[a[live] + at] ^ w8[b[live] + at]
        same = x == 0
        low = x & (~x + U(1))  # lowest differing bit
        out[live + 1] = at + np.where(same, 8, np.log2(np.maximum(low, U(1)).astype(np.float64)).astype(np.int64) // 8)
        live = live[same]
    return np.minimum(out, cap)


# ---------------------------------------------------------------- exchanges

_ANCHORS = "bucket int, block int, once binary, twice binary, many binary"


def _key(fp: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket and 32-bit rest of each anchor."""
    return (((fp >> U(32)) % U(buckets)) << U(32)) | (fp & U(0xFFFFFFFF))


def _anchors(width: int, buckets: int):
    def run(t: pa.Table) -> pa.Table:
        release_encoders()
        block, ids, got = t["block"][0].as_py(), doc_ids(t), []
        for row, buf, off in chunked(t):
            starts, runs, doc, fp = segments(buf, off, width)
            got.append((_key(fp, buckets), ids[row + doc], buf, starts, runs))
        key, doc = np.concatenate([x[0] for x in got]), np.concatenate([x[1] for x in got])
        o = np.argsort(key)
        key, doc = key[o], doc[o]
        if not len(key):
            return pa.table({"bucket": pa.array([], pa.int32()), "block": pa.array([], pa.int32()), **{k: pa.array([], pa.binary()) for k in ("once", "twice", "many")}})
        heads = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        many = np.maximum.reduceat(doc, heads) != np.minimum.reduceat(doc, heads)
        key = key[heads]
        often = np.diff(np.append(heads, len(o))) >= FREQUENT
        which = np.repeat(np.where(often, np.arange(len(heads)), -1), np.diff(np.append(heads, len(o))))
        of = np.empty(len(o), np.int64)
        of[o] = which
        of = np.split(of, np.cumsum([len(x[0]) for x in got])[:-1])
        told = [(a[a >= 0], content_hash(buf, starts[a >= 0], runs[a >= 0] + width - 1)) for a, (_, _, buf, starts, runs) in zip(of, got, strict=True)]
        own, h = np.concatenate([x[0] for x in told]), np.concatenate([x[1] for x in told])
        o = np.lexsort((h, own))
        own, h = own[o], h[o]
        different = np.bincount(own[np.concatenate(([True], (own[1:] != own[:-1]) | (h[1:] != h[:-1])))] if len(own) else own, minlength=len(heads)).astype(np.uint32)
        often = different >= FREQUENT
        b, rest = (key >> U(32)).astype(np.int64), key.astype(np.uint32)
        names = np.unique(b)
        s, e = np.searchsorted(b, names), np.searchsorted(b, names, "right")
        return pa.table({"bucket": pa.array(names, pa.int32()), "block": pa.array(np.full(len(names), block), pa.int32()),
                         "once": pa.array([rest[i:j][~many[i:j]].tobytes() for i, j in zip(s, e, strict=True)], pa.binary()),
                         "twice": pa.array([rest[i:j][many[i:j]].tobytes() for i, j in zip(s, e, strict=True)], pa.binary()),
                         "many": pa.array([np.stack((rest[i:j][often[i:j]], different[i:j][often[i:j]])).tobytes() for i, j in zip(s, e, strict=True)], pa.binary())})

    return run


_SHARED = "block int, bucket int, shared binary, hot binary"


def _shared(hot_blocks: int | None, hot_segments: int):
    """Which anchors of each block several documents have, and which of them are hot: with more than `hot_segments` segments that differ inside their
    blocks (fewer than FREQUENT in a block count as one), or in more than `hot_blocks` blocks where that is given."""

    def run(t: pa.Table) -> pa.Table:
        rows = [(np.frombuffer(a, np.uint32), np.frombuffer(b, np.uint32)) for a, b in zip(t["once"].to_pylist(), t["twice"].to_pylist(), strict=True)]
        value, count = np.unique(np.concatenate([x for r in rows for x in r]), return_counts=True)
        many = np.unique(np.concatenate([r[1] for r in rows]))
        yes = count > 1
        yes[np.searchsorted(value, many)] = True
        volume = count.astype(np.int64)
        for x in t["many"].to_pylist():
            if x:
                rest, different = np.frombuffer(x, np.uint32).reshape(2, -1)
                volume[np.searchsorted(value, rest)] += different - 1  # an anchor is there once a row
        hot = volume > hot_segments
        if hot_blocks is not None:
            hot |= count > hot_blocks
        hot &= yes
        out_s, out_h = [], []
        for r in rows:
            x = np.concatenate(r)
            at = np.searchsorted(value, x)
            out_s.append(x[yes[at] & ~hot[at]].tobytes())
            out_h.append(x[hot[at]].tobytes())
        return pa.table({"block": t["block"].combine_chunks(), "bucket": t["bucket"].combine_chunks(), "shared": pa.array(out_s, pa.binary()), "hot": pa.array(out_h, pa.binary())})

    return run


def _keys(t: pa.Table, column: str) -> np.ndarray:
    got = [(U(b) << U(32)) | np.frombuffer(x, np.uint32).astype(U) for b, x in zip(t["bucket"].to_pylist(), t[column].to_pylist(), strict=True)]
    return np.sort(np.concatenate(got)) if got else np.zeros(0, U)


def _has(keys: np.ndarray, x: np.ndarray) -> np.ndarray:
    return keys[np.minimum(np.searchsorted(keys, x), len(keys) - 1)] == x if len(keys) else np.zeros(len(x), bool)


def _windows(starts: np.ndarray, runs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every window of the given segments, and the segment it is of."""
    seg = np.repeat(np.arange(len(starts)), runs)
    return starts[seg] + np.arange(len(seg)) - (np.cumsum(runs) - runs)[seg], seg


_SEGMENTS = "bucket int, block int, hot boolean, fps binary, docs binary, lens binary, body binary"


def _cut(width: int, buckets: int):
    """The distinct segments of a block that have a shared anchor, each with its smallest document; hot null: the block's hot anchors themselves."""

    def run(docs: pa.Table, marks: pa.Table) -> pa.Table:
        release_memory()
        out: dict[str, list] = {k: [] for k in ("bucket", "block", "hot", "fps", "docs", "lens", "body")}
        if docs.num_rows and marks.num_rows:
            block, ids = docs["block"][0].as_py(), doc_ids(docs)
            for hot, wanted in ((False, _keys(marks, "shared")), (True, _keys(marks, "hot"))):
                got = []
                for row, buf, off in chunked(docs) if len(wanted) else ():
                    starts, runs, doc, fp = segments(buf, off, width)
                    key = _key(fp, buckets)
                    sel = np.flatnonzero(_has(wanted, key))
                    starts, runs, doc, key = starts[sel], runs[sel], doc[sel], key[sel]
                    if hot:
                        starts, seg = _windows(starts, runs)
                        runs, doc = np.ones(len(starts), np.int64), doc[seg]
                        h = content_hash(buf, starts, np.full(len(starts), width))
                        key = _key(h, buckets)
                    else:
                        h = content_hash(buf, starts, runs + width - 1)
                    o = np.lexsort((ids[row + doc], h))
                    o = o[np.concatenate(([True], h[o][1:] != h[o][:-1]))] if len(o) else o
                    lens = (runs[o] + width - 1).astype(np.uint8)
                    at, _ = _windows(starts[o], lens.astype(np.int64))
                    got.append((h[o], key[o], ids[row + doc[o]], lens, buf[at]))
                if not got:
                    continue
                if hot:
                    for k, v in zip(out, (block % buckets, block, None, wanted.tobytes(), b"", b"", b""), strict=True):
                        out[k].append(v)
                h, key, doc, lens, body = (np.concatenate([g[i] for g in got]) for i in range(5))
                ends = np.cumsum(lens.astype(np.int64))
                o = np.lexsort((doc, h, key))
                o = o[np.concatenate(([True], h[o][1:] != h[o][:-1]))] if len(o) else o
                b = (key[o] >> U(32)).astype(np.int64)
                names = np.unique(b)
                for name, s, e in zip(names, np.searchsorted(b, names), np.searchsorted(b, names, "right"), strict=True):
                    i = o[s:e]
                    at, _ = _windows(ends[i] - lens[i], lens[i].astype(np.int64))
                    for k, v in zip(out, (int(name), block, hot, (key[i] & U(0xFFFFFFFF)).astype(np.uint32).tobytes(), doc[i].tobytes(), lens[i].tobytes(), body[at].tobytes()), strict=True):
                        out[k].append(v)
        kinds = (pa.int32(), pa.int32(), pa.bool_(), *[pa.binary()] * 4)
        return pa.table({k: pa.array(v, kind) for (k, v), kind in zip(out.items(), kinds, strict=True)})

    return run


_MARKS = "block int, hot boolean, hashes binary, masks binary"


def _judge(width: int, piece: int = 4 << 20):
    """Which windows of each block's segments a smaller document has: one bit a window.  Blocks' hot anchors (hot null) pass through."""

    def run(t: pa.Table) -> pa.Table:
        release_memory()
        notes = t.filter(pc.is_null(t["hot"]))
        notes = pa.table({"block": notes["block"], "hot": notes["hot"], "hashes": notes["fps"], "masks": notes["body"]})
        t = t.filter(pc.is_valid(t["hot"]))
        if not t.num_rows:
            return notes
        lens_of = [np.frombuffer(x, np.uint8).astype(np.int64) for x in t["lens"].to_pylist()]
        rows = np.repeat(np.arange(t.num_rows), [len(x) for x in lens_of])
        lens = np.concatenate(lens_of)
        fp = np.concatenate([np.frombuffer(x, np.uint32) for x in t["fps"].to_pylist()])
        doc = np.concatenate([np.frombuffer(x, np.int64) for x in t["docs"].to_pylist()])
        body = np.frombuffer(b"".join(t["body"].to_pylist()) + bytes(96), np.uint8)
        starts = np.cumsum(lens) - lens
        hot = t["hot"].to_numpy()[rows]
        h = content_hash(body, starts, lens)
        # equal segments stand for one, with the smallest document of all; hashes only bring them together, their bytes are compared
        o = np.lexsort((h, fp, hot))
        new = np.concatenate(([True], (h[o][1:] != h[o][:-1]) | (fp[o][1:] != fp[o][:-1]) | (hot[o][1:] != hot[o][:-1])))
        if not equal_to_last(body, starts[o], lens[o])[~new].all():  # two segments of one hash: name all by their bytes
            name = np.unique([body[s : s + n].tobytes() for s, n in zip(starts, lens, strict=True)], return_inverse=True)[1]
            o = np.lexsort((name, fp, hot))
            new = np.concatenate(([True], (name[o][1:] != name[o][:-1]) | (fp[o][1:] != fp[o][:-1]) | (hot[o][1:] != hot[o][:-1])))
        which = np.empty(len(o), np.int64)
        which[o] = np.cumsum(new) - 1
        lead = o[new]
        least = np.minimum.reduceat(doc[o], np.flatnonzero(new))
        f = fp[lead].astype(np.int64) * 2 + hot[lead]
        edge = np.flatnonzero(np.concatenate(([True], f[1:] != f[:-1], [True])))
        group = np.repeat(np.arange(len(edge) - 1), np.diff(edge))
        n_windows = lens[lead] - width + 1
        base = np.cumsum(n_windows) - n_windows
        best = np.repeat(least, n_windows)
        todo = np.arange(len(lead))
        bounds = np.cumsum(lens[lead[todo]] + 1)
        s = 0
        while s < len(todo):
            e = max(s + 1, int(np.searchsorted(bounds, (bounds[s - 1] if s else 0) + piece, "right")))
            while e < len(todo) and group[todo[e]] == group[todo[e - 1]]:
                e += 1  # an anchor's segments stay together
            seg = todo[s:e]
            size = lens[lead[seg]]
            at, own = _windows(starts[lead[seg]], size)
            where = np.arange(len(at)) + own  # one 0 behind each segment
            text = np.zeros(len(at) + len(seg), np.uint8)
            text[where] = body[at]
            of = np.repeat(np.arange(len(seg)), size + 1)
            place = np.arange(len(text)) - np.repeat(np.cumsum(size + 1) - size - 1, size + 1)
            order = suffix_order(text, width)
            whole = place[order] + width <= size[of[order]]
            order = order[whole]
            if len(order):
                lcp = common_prefixes(text, order, width)
                first = np.flatnonzero(np.concatenate(([True], lcp[1:] < width)))
                low = np.minimum.reduceat(least[seg[of[order]]], first)
                best[base[seg[of[order]]] + place[order]] = np.repeat(low, np.diff(np.append(first, len(order))))
            s = e
        # one mask an entry, against that block's smallest document of the segment
        nw = lens - width + 1
        win, ent = _windows(base[which], nw)
        bit = (best[win] < doc[ent]).astype(U) << (np.arange(len(ent)) - (np.cumsum(nw) - nw)[ent]).astype(U)
        mask = np.bitwise_or.reduceat(bit, np.cumsum(nw) - nw).astype(np.uint32) if len(nw) else np.zeros(0, np.uint32)
        out_h, out_m = [], []
        for r in range(t.num_rows):
            a, b = np.searchsorted(rows, [r, r + 1])
            yes = np.flatnonzero(mask[a:b]) + a
            out_h.append(h[yes].tobytes())
            out_m.append(mask[yes].tobytes())
        told = pa.table({"block": t["block"], "hot": t["hot"], "hashes": pa.array(out_h, pa.binary()), "masks": pa.array(out_m, pa.binary())})
        return pa.concat_tables([told, notes.cast(told.schema)]).combine_chunks()

    return run


def _least(h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes and the smallest document of each."""
    o = np.lexsort((doc, h))
    heads = np.concatenate(([True], h[o][1:] != h[o][:-1])) if len(o) else np.zeros(0, bool)
    return h[o][heads], doc[o][heads]


def _apply(width: int, buckets: int, with_text: bool, carry: list[str]):
    """Covered bytes of every document of a block, and what is left."""

    def run(docs: pa.Table, marks: pa.Table) -> pa.Table:
        release_memory()
        ids = doc_ids(docs)
        seen: dict[str, list] = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept")}
        kinds = marks["hot"].to_pylist() if marks.num_rows else []
        tell = {}
        for kind in (False, True, None):
            pick = [i for i, x in enumerate(kinds) if x is kind]
            h = np.concatenate([np.frombuffer(marks["hashes"][i].as_py(), U) for i in pick]) if pick else np.zeros(0, U)
            m = np.concatenate([np.frombuffer(marks["masks"][i].as_py(), np.uint32) for i in pick]) if pick and kind is not None else np.zeros(len(h), np.uint32)
            o = np.argsort(h)
            tell[kind] = (h[o], m[o])
        # smallest document of each distinct segment and (hot) window inside the block
        cuts, none = [], np.zeros(0, np.int64)
        for row, buf, off in chunked(docs):
            starts, runs, doc, fp = segments(buf, off, width)
            h = content_hash(buf, starts, runs + width - 1)
            win, own, wh = none, none, none.astype(U)
            if len(tell[None][0]):  # hot anchors: windows one by one
                sel = np.flatnonzero(_has(tell[None][0], _key(fp, buckets)))
                win, seg = _windows(starts[sel], runs[sel])
                own, wh = ids[row + doc[sel]][seg], content_hash(buf, win, np.full(len(win), width))
            cuts.append((row, buf, off, starts, runs, doc, h, win, own, wh))
        uniq, least = _least(np.concatenate([c[6] for c in cuts]), np.concatenate([ids[c[0] + c[5]] for c in cuts])) if cuts else (none.astype(U), none)
        hot_uniq, hot_least = _least(np.concatenate([c[9] for c in cuts]), np.concatenate([c[8] for c in cuts])) if cuts else (none.astype(U), none)
        for row, buf, off, starts, runs, doc, h, hot_win, hot_own, wh in cuts:
            mine = ids[row + doc]
            whole = least[np.searchsorted(uniq, h)] < mine
            hh, mm = tell[False]
            mask = np.zeros(len(h), np.uint32)
            if len(hh):
                at = np.minimum(np.searchsorted(hh, h), len(hh) - 1)
                mask = np.where(hh[at] == h, mm[at], 0).astype(np.uint32)
            busy = np.flatnonzero(whole | (mask > 0))
            win, seg = _windows(starts[busy], runs[busy])
            order = win - starts[busy][seg]
            covered = [win[whole[busy][seg] | ((mask[busy][seg] >> order.astype(np.uint32)) & 1).astype(bool)]]
            if len(wh):
                covered.append(hot_win[_has(tell[True][0], wh) | (hot_least[np.searchsorted(hot_uniq, wh)] < hot_own)])
            c = np.unique(np.concatenate(covered))
            delta = np.zeros(int(off[-1]) + 1, np.int32)
            delta[c] += 1
            np.add.at(delta, c + width, -1)
            gone = np.cumsum(delta[:-1]) > 0
            for i in range(len(off) - 1):
                s, e = int(off[i]), int(off[i + 1])
                g = gone[s:e]
                removed = int(g.sum())
                seen["n_bytes"].append(e - s)
                seen["n_removed"].append(removed)
                seen["n_spans"].append(int(g[0]) + int((g[1:] & ~g[:-1]).sum()) if removed else 0)
                seen["kept"].append(buf[s:e][~g].tobytes() if removed else buf[s:e].tobytes())
        out = {"doc_id": docs["doc_id"].combine_chunks() if docs.num_rows else pa.array([], pa.int64())}
        for k in ("n_bytes", "n_removed", "n_spans"):
            out[k] = pa.array(seen[k], pa.int64())
        out["kept_sha256"] = pa.array([hashlib.sha256(x).hexdigest() for x in seen["kept"]], pa.string())
        if with_text:
            out["kept"] = pa.array(seen["kept"], pa.binary())
            out["kept_text"] = pa.array([x.decode("utf-8", "ignore") for x in seen["kept"]], pa.string())
        for c in carry:
            out[c] = docs[c].combine_chunks() if docs.num_rows else pa.array([], pa.string())
        return pa.table(out)

    return run


# ---------------------------------------------------------------- the operator

def suffix_dedup(docs: DataFrame, width: int = 50, with_text: bool = False, block_bytes: int = 2 << 20, hot_blocks: int | None = None, hot_segments: int = 1 << 15,
                 carry: list[str] | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept: the bytes left; kept_text: their whole characters) of every row of docs,
    and string columns of docs to carry along.

    width: bytes of a string that counts as repeated, from GRAM+1 to GRAM+32.  hot_segments: different segments of an anchor from which they go as
    single windows; hot_blocks: blocks from which they do as well, where given."""
    if not GRAM < width <= GRAM + 31:
        raise ValueError("width out of range")
    carry = carry or []
    docs = slim(docs, *carry)
    n = parts(docs, block_bytes)
    # rows without doc_id are one document, but need not be one block
    blocks = docs.withColumn("block", F.pmod(F.xxhash64(F.coalesce("doc_id", F.xxhash64("text"))), F.lit(n)).cast("int")).repartition(max(1, n // 3), "block")
    marks = blocks.groupBy("block").applyInArrow(_anchors(width, n), _ANCHORS).groupBy("bucket").applyInArrow(_shared(hot_blocks, hot_segments), _SHARED)
    cut = blocks.groupBy("block").cogroup(marks.groupBy("block")).applyInArrow(_cut(width, n), _SEGMENTS)
    told = cut.groupBy("bucket").applyInArrow(_judge(width), _MARKS)
    out = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary, kept_text string" * with_text + "".join(f", {c} string" for c in carry)
    return blocks.groupBy("block").cogroup(told.groupBy("block")).applyInArrow(_apply(width, n, with_text, carry), out)


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(table(spark, sf_dir, "documents"))


QUERIES = {"op2_suffix_dedup": op2_suffix_dedup}

"""Encoding whole texts chunk by chunk, with a bounded cache of chunks per Python worker.

ChunkCache: a single space between two non-space characters always starts a new match of the byte-level splitting pattern, so text
between such spaces can be encoded on its own.  Texts with other white space at a cut are encoded whole.

MatchCache: the chunks are the matches of the tokenizers library's byte-level pattern, found for all texts of a run at once in their
bytes.  Which characters are letters, numbers or white space is asked of the library itself, once a character.
"""

from __future__ import annotations

import sys
import types
from itertools import chain, compress

import numpy as np
import pyarrow as pa

from .textkernel import PAD, text_bytes


def worker_state() -> types.ModuleType:
    """Lives as long as the Python worker; functions that arrive by value share it."""
    return sys.modules.setdefault("_chunk_cache_of_worker", types.ModuleType("_chunk_cache_of_worker"))


#: chunks that are encoded in one go
RUN = 100


class _Known(dict):
    """-2 for what isn't known yet."""

    def __missing__(self, key: str) -> int:
        return -2


class ChunkCache:
    """Chunk -> ids.  `many` encodes a list of strings to lists of ids; at most `limit` chunks are kept."""

    def __init__(self, many, limit: int = 1_380_000):
        self.many, self.limit = many, limit
        self.reset()

    def reset(self) -> None:
        self.at: dict[str, int] = _Known()
        self.lead: dict[str, int] = {}
        self.ids = np.zeros(1 << 20, np.int32)
        self.start = np.zeros(1 << 18, np.int64)
        self.size = np.zeros(1 << 18, np.int64)
        self.n = self.used = 0
        self.end: int | None = None

    def _put(self, rows: list[list[int]]) -> range:
        flat = np.fromiter(chain.from_iterable(rows), np.int32)
        return self._put_flat(flat, np.fromiter(map(len, rows), np.int64, len(rows)))

    def _put_flat(self, flat: np.ndarray, size: np.ndarray) -> range:
        rows = size
        while self.used + len(flat) > len(self.ids):
            self.ids = np.concatenate((self.ids, np.zeros_like(self.ids)))
        while self.n + len(rows) > len(self.start):
            self.start, self.size = (np.concatenate((x, np.zeros_like(x))) for x in (self.start, self.size))
        self.ids[self.used : self.used + len(flat)] = flat
        self.start[self.n : self.n + len(rows)] = self.used + np.cumsum(size) - size
        self.size[self.n : self.n + len(rows)] = size
        self.used += len(flat)
        self.n += len(rows)
        return range(self.n - len(rows), self.n)

    def _put_cut(self, words: list[str]) -> list[int]:
        return list(self._put(self.many([" " + p for p in words])))

    def chunks(self, texts: list[str], end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Chunk numbers of all texts, and how many each text has; with an end_id, a last chunk of that id alone."""
        if self.n > self.limit:
            self.reset()
        split = [t.split(" ") for t in texts]
        rest = [p for s in split for p in s[1:]]
        found = np.fromiter(map(self.at.__getitem__, rest), np.int64, len(rest))
        miss = np.flatnonzero(found == -2)
        if len(miss):
            lost = [rest[i] for i in miss]
            good, unsafe = [], []
            for p in dict.fromkeys(lost):
                (unsafe if not p or p[0].isspace() or p[-1].isspace() else good).append(p)
            self.at.update(zip(good, self._put_cut(good), strict=True))
            self.at.update(dict.fromkeys(unsafe, -1))
            found[miss] = np.fromiter(map(self.at.__getitem__, lost), np.int64, len(lost))
        heads = [s[0] if not s[0][-1:].isspace() or len(s) == 1 else None for s in split]
        new = [p for p in set(heads) if p is not None and p not in self.lead]
        self.lead.update(zip(new, self._put(self.many(new)), strict=True))
        counts = np.fromiter(map(len, split), np.int64, len(split))
        ends = np.cumsum(counts)
        out = np.empty(int(ends[-1]) if len(ends) else 0, np.int64)
        first = np.zeros(len(out), bool)
        first[ends - counts] = True
        out[~first] = found
        out[first] = [-1 if h is None else self.lead[h] for h in heads]
        bad = np.minimum.reduceat(out, ends - counts) < 0 if len(out) else np.zeros(0, bool)
        if bad.any():
            who = np.flatnonzero(bad)
            whole = self._put(self.many([texts[i] for i in who]))
            keep = ~np.repeat(bad, counts)
            keep[(ends - counts)[who]] = True
            out[(ends - counts)[who]] = whole
            out = out[keep]
            counts[who] = 1
        return self._ended(out, counts, end_id)

    def _ended(self, out: np.ndarray, counts: np.ndarray, end_id: int | None) -> tuple[np.ndarray, np.ndarray]:
        if end_id is None:
            return out, counts
        if self.end != end_id:
            self.end, self.end_at = end_id, self._put([[end_id]])[0]
        last = np.cumsum(counts + 1) - 1
        longer = np.full(len(out) + len(counts), self.end_at, np.int64)
        mask = np.ones(len(longer), bool)
        mask[last] = False
        longer[mask] = out
        return longer, counts + 1

    def gather(self, chunk: np.ndarray) -> np.ndarray:
        size = self.size[chunk]
        return self.ids[np.repeat(self.start[chunk] - (np.cumsum(size) - size), size) + np.arange(size.sum())]

    def encode(self, texts: list[str] | pa.ChunkedArray, end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in one array, and the number each has."""
        chunk, counts = self.chunks(texts, end_id)
        sums = np.concatenate(([0], np.cumsum(self.size[chunk])))
        ends = np.cumsum(counts)
        return self.gather(chunk), sums[ends] - sums[ends - counts]


#: classes of characters; 0 stands before a text and behind it
LETTER, NUMBER, OTHER, SPACE, UNASKED = 1, 2, 3, 4, 255


class Splitter:
    """Starts of the matches of `'(?:[sdmt]|ll|ve|re)| ?\\p{L}+| ?\\p{N}+| ?[^\\s\\p{L}\\p{N}]+|\\s+(?!\\S)|\\s+`, which cover every text."""

    def __init__(self, split):
        self.split = split  # text -> [(match, (from, to))] in characters
        self.kind = np.full(0x110000, UNASKED, np.uint8)
        self._ask(np.arange(128))

    def _ask(self, points: np.ndarray) -> None:
        """A character belongs with the letter, digit or mark that it continues; white space continues none."""
        starts = {at for _, (at, _) in self.split("".join("a{0}1{0}!{0}\n".format(chr(c)) for c in points))}
        for i, c in enumerate(points.tolist()):
            self.kind[c] = next((k for k, at in ((LETTER, 1), (NUMBER, 3), (OTHER, 5)) if 7 * i + at not in starts), SPACE)

    def _points(self, data: np.ndarray, lead: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Code points of the characters of `size` UTF-8 bytes at `lead`."""
        out = data[lead].astype(np.int64) & (0xFF >> (size + 1))
        for k in range(1, 4):
            more = size > k
            out[more] = out[more] << 6 | data[lead[more] + k] & 63
        return out

    def starts(self, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Places in `data` (all texts, with zeros behind) where a match starts."""
        n = int(off[-1])
        if not n:
            return np.zeros(0, np.int64)
        d = data[:n]
        kind = self.kind[:256][d]
        wide = np.flatnonzero(d > 0xBF)
        size = np.searchsorted([0xE0, 0xF0], d[wide], "right") + 2
        points = self._points(data, wide, size)
        new = np.unique(points[self.kind[points] == UNASKED])
        if len(new):
            self._ask(new)
        of = self.kind[points]
        for k in range(4):
            more = size > k
            kind[wide[more] + k] = of[more]
        full = off[1:] > off[:-1]
        first, last = off[:-1][full], off[1:][full] - 1
        before, after = np.zeros(n, np.uint8), np.zeros(n + PAD, np.uint8)
        before[1:], after[: n - 1] = kind[:-1], kind[1:]
        before[first] = after[last] = 0
        blanks = np.flatnonzero(of == SPACE)  # white space of several bytes is seen from its first byte
        after[wide[blanks]] = after[wide[blanks] + size[blanks] - 1]
        space = kind == SPACE
        # white space goes together but for its last character, if something follows: a space then starts the next match, all else is one of its own
        cut = kind != before
        cut[1:] &= space[1:] | (d[:-1] != 0x20)
        cut |= space & (before == SPACE) & (after[:n] != SPACE) & (after[:n] != 0)
        cut[first] = True
        for k in range(1, 3):
            inner = wide[blanks][size[blanks] > k] + k
            cut[inner] = False
        mark = np.flatnonzero(cut & (d == 0x27))
        mark = mark[after[mark] == LETTER]
        a, b = data[mark + 1], data[mark + 2]
        one = np.isin(a, np.frombuffer(b"sdmt", np.uint8))
        two = (after[mark + 1] == LETTER) & (((a == 0x6C) & (b == 0x6C)) | (((a == 0x76) | (a == 0x72)) & (b == 0x65)))
        cut[mark[one | two] + 1] = False
        ends = mark[one | two] + np.where(one, 2, 3)[one | two]
        cut[ends[ends < n]] = True
        return np.flatnonzero(cut)


class MatchCache(ChunkCache):
    """Chunks are matches of the pattern (whole texts where `splitter` is None).  Takes a string column, null counts as empty."""

    def __init__(self, many, splitter: Splitter | None, line: int | None = None, limit: int = 1_380_000):
        super().__init__(many, limit)
        self.splitter, self.line = splitter, line

    def _put_new(self, words: list[str]) -> np.ndarray:
        """Numbers of new chunks.  Those without white space, but for a space in front, are encoded in runs joined by line ends, which are
        matches of their own with one id (`line`) that nothing else in such chunks has."""
        out = np.full(len(words), -1, np.int64)
        if self.splitter is not None and self.line is not None:
            simple = np.fromiter((w != " " and w.isprintable() for w in words), bool, len(words))  # no printable character but the space is white space
            plain = list(compress(words, simple))
            got = self.many(["\n".join(plain[k : k + RUN]) + "\n" for k in range(0, len(plain), RUN)])
            flat = np.concatenate([np.array(r, np.int32) for r in got]) if got else np.zeros(0, np.int32)
            cuts = np.flatnonzero(flat == self.line)
            if len(cuts) == len(plain):
                out[simple] = self._put_flat(np.delete(flat, cuts), np.diff(cuts, prepend=-1) - 1)
        rest = np.flatnonzero(out < 0)
        out[rest] = self._put(self.many([words[i] for i in rest]))
        return out

    def chunks(self, texts: pa.ChunkedArray, end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Chunk numbers of all texts, and how many each text has; with an end_id, a last chunk of that id alone."""
        if self.n > self.limit or self.splitter is None:  # whole texts are not kept
            self.reset()
        data, off = text_bytes(texts)
        starts = self.splitter.starts(data, off) if self.splitter is not None else off[:-1][off[1:] > off[:-1]]
        bounds = np.append(starts, off[-1])
        each = pa.Array.from_buffers(pa.large_string(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(data)]).dictionary_encode()
        words = each.dictionary.to_numpy(zero_copy_only=False).tolist()  # much faster than to_pylist
        found = np.fromiter(map(self.at.__getitem__, words), np.int64, len(words))
        miss = np.flatnonzero(found == -2)
        if len(miss):
            new = [words[i] for i in miss]
            found[miss] = self._put_new(new)
            self.at.update(zip(new, found[miss].tolist(), strict=True))
        return self._ended(found[each.indices.to_numpy()], np.diff(np.searchsorted(starts, off)), end_id)


def library_cache(path: str) -> MatchCache:
    """The tokenizers library behind a cache, one a worker and file."""
    held = worker_state()
    name = "json:" + path
    if not hasattr(held, name):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, models, pre_tokenizers

        tool = Tokenizer.from_file(path)
        tool.encode_special_tokens = True
        tool.no_padding()
        tool.no_truncation()
        many = lambda xs: [e.ids for e in tool.encode_batch_fast(xs, add_special_tokens=False)] if xs else []
        line = many(["\n"])[0]
        by = tool.pre_tokenizer
        alone = (isinstance(by, pre_tokenizers.ByteLevel) and by.use_regex and not by.add_prefix_space and tool.normalizer is None and isinstance(tool.model, models.BPE)
                 and all(t.special for t in tool.get_added_tokens_decoder().values()))  # each match is encoded by itself
        setattr(held, name, MatchCache(many, Splitter(by.pre_tokenize_str) if alone else None, line=line[0] if len(line) == 1 else None))
    return getattr(held, name)

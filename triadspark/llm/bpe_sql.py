"""Byte-level BPE by recursive SQL inside each task.

Every Python worker holds an in-process SQL database with two tables made from a rank file: the vocabulary, and all merges
(two ids whose bytes together are a token; its id is its rank).  New words become rows (word, position, id), one a byte.  A recursive query
joins neighbours to the merge table and contracts each word's leftmost pair of the least rank, until no word has such a pair.  A long word
goes alone to a second recursive query, which contracts at once all pairs that are the least far around.
Words that are tokens themselves are looked up at once, as the rank library does.  Decoding is an ordered aggregation of token texts.

Words recur, so ids of chunks between single spaces are kept in a bounded cache per worker; only new chunks reach the query.

Edge cases: null text is empty (no ids).  Special tokens do not exist: their strings are ordinary text.  Rows may repeat; doc_id may be null.  Empty
tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from itertools import chain, compress, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import slim, table
from .encoding import ChunkCache, worker_state
from .textkernel import pieces

#: bytes from which a word goes to the query for one long word
LONG_WORD = 1000

CONTRACT = """
with recursive state as (
  select w, p, id, 0 as round from seed
  union all
  (with near as materialized (
     select w, p, id, round, lead(id) over o as next_id, lag(p) over o as prev_p from state window o as (partition by w order by p)),
   best as (
     select n.w, min((m.merged::bigint << 32) | n.p) as k from near n join merges m on m.a = n.id and m.b = n.next_id group by n.w)
   select n.w, n.p, case when n.p = k & 4294967295 then (k >> 32)::int else n.id end, n.round + 1
   from near n join best on n.w = best.w where n.prev_p is distinct from k & 4294967295)
)
select s.w, list(s.id order by s.p) as ids
from state s join (select w, max(round) as last from state group by w) l on s.w = l.w and s.round = l.last
group by s.w order by s.w
"""

#: One long word, state kept by place (a contracted place has id -1).  A pair is contracted in a round if no pair within {reach} places on either side has a
#: lesser rank, and if it is the leftmost of that rank there, or neither it nor any pair before it there would make, with its neighbours as they are or
#: with a second such token, a pair of lesser rank.  Of a run of overlapping pairs of one
#: rank every other one is, from the run's head on, as far as all of them are the least around them.  Only a token that grows place by place from outside could forestall it, and it would need more bytes than any token of the word's bytes has.
#: So every such pair is one that contracting the leftmost pair of the least rank, time after time, arrives at too.
CONTRACT_LONG = """
with recursive state(p, id) using key (p) as (
  select p, id from seed
  union
  (with live as (select p, id, lag(id) over o as prev_id, lead(id) over o as next_id, lead(p) over o as next_p, lead(id, 2) over o as after_id from recurring.state where id >= 0 window o as (order by p)),
   pairs as materialized (select l.p, l.next_p, m.merged as r, prev_id, after_id, m.risky from live l left join merges m on m.a = l.id and m.b = l.next_id),
   bad as (select x.p from pairs x join lower m on m.a = x.prev_id and m.b = x.r and m.merged < x.r where x.risky
     union select x.p from pairs x join lower m on m.a = x.r and m.b = x.after_id and m.merged < x.r where x.risky
     union select x.p from pairs x join lower m on m.a = x.r and m.b = x.r and m.merged < x.r where x.risky),
   near as (select pairs.p, next_p, r, min(r) over w as least, min(r) over b as ahead, max(bad.p) over b as danger, bad.p as own, lag(r) over o as last, row_number() over o as n
     from pairs left join bad on bad.p = pairs.p
     window o as (order by pairs.p), w as (order by pairs.p rows between {reach} preceding and {reach} following), b as (order by pairs.p rows between {reach} preceding and 1 preceding)),
   runs as (select *, max(case when last is distinct from r then n end) over (order by p) as head, max(case when r is distinct from least then n else 0 end) over (order by p) as unsafe from near),
   pick as materialized (select p, next_p, r from runs where r = least and (ahead is null or ahead > r or (danger is null and own is null and unsafe < head and (n - head) % 2 = 0)))
   select p, r from pick union all select next_p, -1 from pick)
)
select id from state where id >= 0 order by p
"""


class WordChunks(ChunkCache):
    """A chunk of letters alone is one match of a pattern that has ` ?\\p{L}+`, and goes to the query without splitting."""

    def __init__(self, bpe: SqlBpe, limit: int):
        super().__init__(bpe.chunk_ids, limit=limit)
        self.bpe = bpe

    def reset(self) -> None:
        super().reset()
        self.marks: dict[str, int] = {}  # words without a leading space

    def _put_cut(self, words: list[str]) -> list[int]:
        # letters below U+0250 are the same in every version of Unicode
        plain = [w.isalpha() and (w.isascii() or max(w) < "\u0250") for w in words] if self.bpe.letter_runs else [False] * len(words)
        out = np.empty(len(words), np.int64)
        mask = np.array(plain, bool)
        letters = list(compress(words, plain))
        out[mask] = self._put_flat(*self.bpe.flat_words([(" " + w).encode() for w in letters]))
        self.at.update(zip(letters, out[mask].tolist(), strict=True))  # chunks with marks at such words find them
        out[~mask] = self._put_flat(*self.bpe.flat_chunks([" " + w for w, p in zip(words, plain, strict=True) if not p]))
        return out.tolist()


class SqlBpe:
    """Encoder and decoder over one rank file."""

    def __init__(self, path: str, pattern: str, known: int = 1_000_000):
        import duckdb
        import regex

        self.split = regex.compile(pattern).findall
        self.letter_runs = r"| ?\p{L}+|" in pattern
        with open(path, "rb") as f:
            self.rank = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        triples = [(self.rank[t[:i]], self.rank[t[i:]], r) for t, r in self.rank.items() for i in range(1, len(t)) if t[:i] in self.rank and t[i:] in self.rank]
        self.single = np.array([self.rank.get(bytes([b]), -1) for b in range(256)], np.int32)
        self.db = duckdb.connect(":memory:", config={"threads": 1, "memory_limit": "300MB"})
        a, b, m = (np.array(x, np.int32) for x in zip(*triples, strict=True)) if triples else (np.zeros(0, np.int32),) * 3
        lower = np.unique(np.concatenate((a[m < a], b[m < b])))  # tokens that are in a pair of lesser rank than their own
        merges = pa.table({"a": a, "b": b, "merged": m, "risky": np.isin(m, lower)})  # noqa: F841
        self.db.execute("create table merges as select * from merges")
        self.db.execute("create table lower as select a, b, merged from merges where merged < a or merged < b")
        # token bytes as characters 256..511, one a byte, so that texts aggregate as strings
        vocab = pa.table({"id": np.array(list(self.rank.values()), np.int32), "piece": ["".join(chr(256 + x) for x in t) for t in self.rank]})  # noqa: F841
        self.db.execute("create table vocab as select * from vocab")
        self.names = [str(i) for i in range(max(self.rank.values(), default=0) + 1)]
        self.cache = WordChunks(self, limit=known)

    def _arrow(self, query: str) -> pa.Table:
        return self.db.sql(query).to_arrow_table()

    def _longest(self, word: bytes) -> int:
        """Bytes of the longest token that has only bytes of the word."""
        if not hasattr(self, "token_bytes"):
            self.token_bytes = np.zeros((len(self.rank), 256), bool)
            size = np.fromiter(map(len, self.rank), np.int64, len(self.rank))
            self.token_bytes[np.repeat(np.arange(len(size)), size), np.frombuffer(b"".join(self.rank), np.uint8)] = True
            self.token_bytes, self.token_size = np.packbits(self.token_bytes, axis=1), size
        absent = np.ones(256, bool)
        absent[np.frombuffer(word, np.uint8)] = False
        return int(self.token_size[~(self.token_bytes & np.packbits(absent)).any(axis=1)].max(initial=1))

    def long_word(self, word: bytes) -> np.ndarray:
        """Ids of one word that is no token, in rounds whose number hardly grows with its length."""
        raw = np.frombuffer(word, np.uint8)
        self.db.register("seed", pa.table({"p": np.arange(len(raw), dtype=np.int32), "id": self.single[raw]}))
        got = self._arrow(CONTRACT_LONG.format(reach=max(1, self._longest(word) - 1)))["id"].combine_chunks().to_numpy()
        self.db.unregister("seed")
        return got

    def flat_words(self, new: list[bytes], step: int = 40_000) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in one array and their number for each, by the recursive query where a word is no token itself."""
        flats, sizes = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
        for at in range(0, len(new), step):
            run = new[at : at + step]
            token = np.fromiter(map(self.rank.get, run, repeat(-1)), np.int32, len(run))
            if max(map(len, run)) > LONG_WORD:
                flat, size = self._with_long(run, token)
                flats.append(flat)
                sizes.append(size)
                continue
            size = np.ones(len(run), np.int64)
            todo = np.flatnonzero(token < 0)
            if len(todo):
                long = [run[i] for i in todo]
                n = np.fromiter(map(len, long), np.int64, len(long))
                raw = np.frombuffer(b"".join(long), np.uint8)
                seed = pa.table({"w": np.repeat(np.arange(len(long), dtype=np.int32), n), "p": np.arange(len(raw)) - np.repeat(np.cumsum(n) - n, n), "id": self.single[raw]})
                self.db.register("seed", seed)
                got = self._arrow(CONTRACT)["ids"].combine_chunks()
                self.db.unregister("seed")
                size[todo] = np.diff(got.offsets.to_numpy())
                flat = np.empty(int(size.sum()), np.int32)
                by_query = np.repeat(token < 0, size)
                flat[by_query] = got.flatten().to_numpy()
                flat[~by_query] = token[token >= 0]
            else:
                flat = token
            flats.append(flat)
            sizes.append(size)
        return np.concatenate(flats), np.concatenate(sizes)

    def _with_long(self, run: list[bytes], token: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for words some of which are long."""
        short = [w for w, k in zip(run, token.tolist(), strict=True) if k >= 0 or len(w) <= LONG_WORD]
        flat, size = self.flat_words(short)
        ends = np.cumsum(size).tolist()
        rows = iter([flat[e - n : e] for e, n in zip(ends, size.tolist(), strict=True)])
        every = [next(rows) if k >= 0 or len(w) <= LONG_WORD else self.long_word(w) for w, k in zip(run, token.tolist(), strict=True)]
        return np.concatenate(every).astype(np.int32), np.fromiter(map(len, every), np.int64, len(every))

    def flat_chunks(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all chunks in one array and their number for each; words are encoded once, by their number in the cache."""
        split = list(map(self.split, chunks))
        every = list(chain.from_iterable(split))
        held, known, fresh = self.cache, {}, []
        for w in dict.fromkeys(every):
            k = held.at[w[1:]] if w[0] == " " and len(w) > 1 else held.marks.get(w, -1)
            if k >= 0:
                known[w] = k
            else:
                fresh.append(w)
        known.update(zip(fresh, held._put_flat(*self.flat_words([w.encode() for w in fresh])), strict=True))
        for w in fresh:
            if w[0] != " " or len(w) == 1:
                held.marks[w] = known[w]
            elif held.at.get(w[1:], -2) == -2:
                held.at[w[1:]] = known[w]
        at = np.fromiter(map(known.__getitem__, every), np.int64, len(every))
        ends = np.concatenate(([0], np.cumsum(held.size[at])))
        last = np.cumsum(np.fromiter(map(len, split), np.int64, len(split)))
        return held.gather(at), np.diff(ends[last], prepend=0)

    def chunk_ids(self, chunks: list[str]) -> list[list[int]]:
        flat, size = self.flat_chunks(chunks)
        ends, ids = np.cumsum(size).tolist(), flat.tolist()
        return [ids[e - n : e] for e, n in zip(ends, size.tolist(), strict=True)]

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> list[bytes]:
        """Bytes of each run of ids."""
        doc = np.repeat(np.arange(len(counts), dtype=np.int32), counts)
        self.db.register("tokens", pa.table({"d": doc, "p": np.arange(len(ids), dtype=np.int32), "id": ids}))
        got = self._arrow("select d, string_agg(piece, '' order by p) as s from tokens join vocab using (id) group by d")
        self.db.unregister("tokens")
        out = [b""] * len(counts)
        for d, s in zip(got["d"].to_pylist(), got["s"].to_pylist(), strict=True):
            out[d] = s.encode("utf-16-le")[::2]
        return out


def sql_bpe(path: str, pattern: str, known: int = 1_000_000) -> SqlBpe:
    held = worker_state()
    name = f"ranks:{known}:{path}{pattern}"
    if not hasattr(held, name):
        setattr(held, name, SqlBpe(path, pattern, known))
    return getattr(held, name)


def _id_runs(counts: np.ndarray, limit: int = 1 << 17) -> Iterator[tuple[int, int]]:
    """Stretches of texts with at most `limit` ids together (a longer text stands alone)."""
    ends, at = np.cumsum(counts), 0
    while at < len(counts):
        upto = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + limit, "right")))
        yield at, upto
        at = upto


def _round_trip(path: str, pattern: str, full: bool, known: int, run_bytes: int):
    def run(batches):
        for batch in batches:
            for t in pieces(batch, "text", run_bytes):
                bpe = sql_bpe(path, pattern, known)
                ids, counts = bpe.cache.encode(t["text"].fill_null("").to_pylist())
                ends = np.cumsum(counts)
                sha, sha_back, back = [], [], []
                for lo, hi in _id_runs(counts):  # a run's strings and its decoding take many times the memory of its ids
                    own = ids[ends[lo] - counts[lo] : ends[hi - 1]]
                    digits, base = list(map(bpe.names.__getitem__, own.tolist())), ends[lo] - counts[lo]
                    sha += [hashlib.sha256(",".join(digits[s:e]).encode()).hexdigest() for s, e in zip((ends - counts - base)[lo:hi], (ends - base)[lo:hi], strict=True)]
                    del digits
                    texts = bpe.decode(own, counts[lo:hi])
                    sha_back += [hashlib.sha256(x).hexdigest() for x in texts]
                    back += texts if full else []
                cols = [t["doc_id"].combine_chunks(), pa.array(counts), pa.array(sha, pa.string()), pa.array(sha_back, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if full:
                    cols += [pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)), pa.int32()), pa.array(ids, pa.int32())), pa.array(back, pa.binary())]
                    names += ["ids", "decoded"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def bpe_round_trip(docs: DataFrame, path: str, pattern: str, full: bool = False, known: int = 1_000_000, run_bytes: int = 6 << 20) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (full: also ids and decoded bytes) of every row of docs.  A worker remembers the ids of about
    `known` chunks and takes runs of `run_bytes` text: less of both is less memory and more time."""
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded binary" * full
    return slim(docs).mapInArrow(_round_trip(path, pattern, full, known, run_bytes), schema)


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as tok

    return bpe_round_trip(table(spark, sf_dir, "documents"), tok.path("byte_bpe_multi_50k.tiktoken"), tok.PATTERN)


QUERIES = {"op6_byte_bpe": op6_byte_bpe}

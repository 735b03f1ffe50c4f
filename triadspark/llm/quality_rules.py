"""Quality rules: counts of a text, and its divergence from its language.

Per document two histograms are taken in one pass: character classes, and the common words of its language.  Summed over
all documents that pass the base rule they are the language's reference.  The verdict is the Jensen-Shannon distance
(base 2, 0 to 1) of both histograms to the reference; documents below a number of words or characters are not judged by it.

Edge cases: null or empty text has no words and fails the base rule.  A null or unlisted language goes with all other unlisted ones.  Repeated rows
give a row each; a null doc_id stays null.  Empty tables give no rows.  Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slim, stored, table
from .textkernel import LOWER, NOT_SPACE, inside_text, pieces, release_encoders, span_hash, text_bytes, word_hash, words

#: fixed values: common words by language
COMMON = {
    "en": "the of and to in a is that for it was on with as be at by this are or from".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als".split(),
    "fr": "de la le et les des en un du une que est pour qui dans par sur plus au avec".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al".split(),
}
LANGS = [*COMMON, "other"]
#: fixed values: symbols of the base rule
SYMBOLS = "#*$%&|<>"
N_CLASS, N_WORD = 8, 1 + max(map(len, COMMON.values()))

_CLASS = np.full(256, 6, np.int64)  # other marks
_CLASS[0x61:0x7B] = 0
_CLASS[0x41:0x5B] = 1
_CLASS[0x30:0x3A] = 2
_CLASS[[0x20, *range(0x09, 0x0E)]] = 3
_CLASS[[ord(c) for c in ".,;:!?'\"()-"]] = 4
_CLASS[[ord(c) for c in SYMBOLS]] = 5
_CLASS[0x80:] = 7
_START = np.ones(256, bool)
_START[0x80:0xC0] = False  # bytes that continue a character
_SYM = np.zeros(256, bool)
_SYM[[ord(c) for c in SYMBOLS]] = True
_NOT_LINE = np.ones(256, bool)
_NOT_LINE[0x0A] = False


def _tables() -> list[tuple[np.ndarray, np.ndarray]]:
    """Sorted hashes of each language's common words and their bins."""
    out = []
    for lang in LANGS:
        ws = list(dict.fromkeys(COMMON.get(lang, [w for ws in COMMON.values() for w in ws[:5]])))[: N_WORD - 1]
        buf, off = text_bytes(pa.array([w for w in ws]))
        h = word_hash(buf, off[:-1], np.diff(off))
        o = np.argsort(h)
        out.append((h[o], o + 1))
    return out


def per_text(flag: np.ndarray, off: np.ndarray) -> np.ndarray:
    c = np.concatenate(([0], np.cumsum(flag)))
    return c[off[1:]] - c[off[:-1]]


def measure(text: pa.Array, lang: np.ndarray) -> dict[str, np.ndarray]:
    """All counts and both histograms of a piece of texts; lang holds positions in LANGS."""
    buf, off = text_bytes(text)
    n, size = len(off) - 1, int(off[-1])
    raw = buf[:size]
    starts, lens, counts = words(buf, off, NOT_SPACE)
    h = word_hash(buf, starts, lens)
    doc = np.repeat(np.arange(n), counts)
    out = {"n_words": counts, "word_chars": per_text(_START[raw] & NOT_SPACE[raw], off), "n_symbols": per_text(_SYM[raw], off)}
    # lines: runs without \\n; those without a word don't count
    ls, ll, lc = words(buf, off, _NOT_LINE)
    word_at = np.concatenate(([0], np.cumsum(np.bincount(starts, minlength=size + 1)[:size]))) if size else np.zeros(1, np.int64)
    ld = np.repeat(np.arange(n), lc)
    full = word_at[ls + ll] > word_at[ls] if len(ls) else np.zeros(0, bool)
    lh, ld = word_hash(buf, ls[full], ll[full]), ld[full]
    o = np.lexsort((lh, ld))
    again = (lh[o][1:] == lh[o][:-1]) & (ld[o][1:] == ld[o][:-1]) if len(o) else np.zeros(0, bool)
    out["n_dup_lines"] = np.bincount(ld[o][1:][again], minlength=n) if len(o) else np.zeros(n, np.int64)
    # words inside 3-word windows that the text has twice or more
    w3 = np.flatnonzero(inside_text(counts, 3))
    s3 = span_hash(h, 3)[w3]
    d3 = doc[w3]
    o = np.lexsort((s3, d3))
    same = (s3[o][1:] == s3[o][:-1]) & (d3[o][1:] == d3[o][:-1]) if len(o) else np.zeros(0, bool)
    rep = np.zeros(len(o), bool)
    if len(o):
        rep[1:] |= same
        rep[:-1] |= same
    at = w3[o[rep]]
    hit = np.zeros(len(h), bool)
    for j in range(3):
        hit[at + j] = True
    out["n_repeat_words"] = np.bincount(doc[hit], minlength=n)
    where = np.repeat(np.arange(n), np.diff(off))
    out["classes"] = np.bincount(where * N_CLASS + _CLASS[raw], minlength=n * N_CLASS).reshape(n, N_CLASS)
    # common words regardless of case, without marks at their ends
    inner = words(LOWER[buf], off, (_CLASS == 0) | (_CLASS == 7))
    ih = word_hash(LOWER[buf], inner[0], inner[1])
    idoc = np.repeat(np.arange(n), inner[2])
    bins = np.zeros(len(ih), np.int64)
    for k, (keys, bin_) in enumerate(_tables()):
        mine = np.flatnonzero(lang[idoc] == k)
        p = np.minimum(np.searchsorted(keys, ih[mine]), len(keys) - 1)
        bins[mine] = np.where(keys[p] == ih[mine], bin_[p], 0)
    out["common"] = np.bincount(idoc * N_WORD + bins, minlength=n * N_WORD).reshape(n, N_WORD)
    return out


_COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
_MEASURED = "doc_id long, lang_no int, " + ", ".join(f"{c} long" for c in _COUNTS) + ", classes array<long>, common array<long>"


def _measured(batches):
    release_encoders()
    for batch in batches:
        for t in pieces(batch, "text", 1 << 19):  # its counts take some 60 bytes of memory a byte
            lang = np.array([LANGS.index(x) if x in COMMON else len(LANGS) - 1 for x in t["lang"].to_pylist()], np.int64)
            m = measure(t["text"], lang)
            rows = lambda x: pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([t["doc_id"].combine_chunks(), pa.array(lang, pa.int32()), *(pa.array(m[c].astype(np.int64)) for c in _COUNTS), rows(m["classes"]), rows(m["common"])],
                                             names=["doc_id", "lang_no", *_COUNTS, "classes", "common"])


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance of each row of counts p to the counts q."""
    p = p / np.maximum(p.sum(axis=1, keepdims=True), 1)
    q = q / max(q.sum(), 1)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        a = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1)
        b = np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    return np.sqrt(np.maximum((a + b) / 2, 0))


def _distances(refs: dict[int, tuple[list[int], list[int]]]):
    def run(batches):
        for batch in batches:
            t = pa.Table.from_batches([batch])
            n = t.num_rows
            lang = t["lang_no"].to_numpy()
            grids = [np.array(t[c].to_pylist(), float).reshape(n, -1) for c in ("classes", "common")]
            out = [np.zeros(n), np.zeros(n)]
            for k, ref in refs.items():
                at = np.flatnonzero(lang == k)
                for j in range(2):
                    if len(at):
                        out[j][at] = js_distance(grids[j][at], np.array(ref[j], float))
            yield pa.RecordBatch.from_arrays([*(t[c].combine_chunks() for c in ("doc_id", *_COUNTS)), pa.array(np.round(out[0], 6)), pa.array(np.round(out[1], 6))], names=["doc_id", *_COUNTS, "js_chars", "js_words"])

    return run


def judge_quality(docs: DataFrame, js_chars: float = 0.33, js_words: float = 0.42, least_words: int = 60, least_chars: int = 300) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, js_chars, js_words of every row of docs."""
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    seen = stored(slim(docs, lang.alias("lang")).mapInArrow(_measured, _MEASURED), "quality-counts")
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    # one row a listed language
    refs = {r["lang_no"]: ([r[f"c{i}"] or 0 for i in range(N_CLASS)], [r[f"w{i}"] or 0 for i in range(N_WORD)]) for r in seen.where(~failed).groupBy("lang_no").agg(
        *(F.sum(F.get("classes", F.lit(i))).alias(f"c{i}") for i in range(N_CLASS)), *(F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(N_WORD))).collect()}
    schema = "doc_id long, " + ", ".join(f"{c} long" for c in _COUNTS) + ", js_chars double, js_words double"
    far = (F.col("n_words") >= least_words) & (F.col("word_chars") >= least_chars) & ((F.col("js_chars") > js_chars) | (F.col("js_words") > js_words))
    return seen.mapInArrow(_distances(refs), schema).select("doc_id", *_COUNTS, failed.alias("base_failed"), (~failed & ~far).alias("kept"), "js_chars", "js_words")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_quality(table(spark, sf_dir, "documents"))


QUERIES = {"op3_quality_rules": op3_quality_rules}

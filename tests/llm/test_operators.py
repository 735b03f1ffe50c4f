"""Operators against brute force on small tables, with nulls, empty and long texts, ties and repeated rows."""

import base64
import collections
import hashlib
import re
import time
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from conftest import rows
from pyspark.sql.functions import lit as F_lit

from triadspark.llm import bpe_sql, decontamination, jaccard_join, licenses, lm_scores, quality_rules, sharding, suffix_dedup, token_counts, token_file
from triadspark.llm.queries import QUERIES, SQL

JSON = public_tokenizers.path("byte_bpe_50k.json")
RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
P1 = "one two three four five six seven eight nine ten eleven twelve thirteen"
ODD = [(1, P1 + " mit license"), (2, P1 + " MIT license"), (3, None), (4, ""), (5, "  a  b\n\n c\t"), (6, "é日本 ü " * 60), (7, "x" * 5000), (8, "All rights reserved. CC BY " * 3), (8, "All rights reserved. CC BY " * 3), (9, P1[4:]), (None, P1), (10, "\n".join(["same line"] * 4)),
       (11, "word " * 80), (12, "Permission is hereby granted, free of charge, to any person obtaining a copy of this software")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(d, t, "x", 1, 2, "en") for d, t in ODD], "doc_id long, text string, block string, part int, bucket int, lang string").repartition(3)


@pytest.fixture(scope="module")
def plain(spark, sf):
    return [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]


@pytest.mark.parametrize("name", sorted(SQL))
def test_oracle(spark, sf, duck, name):
    got, want = QUERIES[name](spark, sf).toPandas(), duck.execute(SQL[name]).df()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols and rows(got, cols) == rows(want, cols)


def brute_dedup(table, width=50):
    first = {}
    key = lambda d: (1 << 63) - 1 if d is None else d
    for d, t in table:
        b = (t or "").encode()
        for i in range(len(b) - width + 1):
            first[b[i : i + width]] = min(first.get(b[i : i + width], 1 << 63), key(d))
    out = []
    for d, t in table:
        b = (t or "").encode()
        g = bytearray(len(b))
        for i in range(len(b) - width + 1):
            if first[b[i : i + width]] < key(d):
                g[i : i + width] = b"\1" * width
        out.append((d, len(b), sum(g), len([x for x in bytes(g).split(b"\0") if x]), hashlib.sha256(bytes(x for x, y in zip(b, g, strict=True) if not y)).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("hot", [1, 256])
def test_suffix_dedup(odd, hot):
    got = [tuple(r) for r in suffix_dedup.suffix_dedup(odd, hot_blocks=hot, block_bytes=1 << 14).collect()]
    assert sorted(got, key=str) == brute_dedup(ODD)


def test_suffix_dedup_table(spark, sf, plain):
    assert sorted((tuple(r) for r in QUERIES["op2_suffix_dedup"](spark, sf).collect()), key=str) == brute_dedup(plain)


@pytest.mark.parametrize("limits", [{"hot_blocks": 1}, {"hot_segments": 20}])
def test_suffix_dedup_frequent_string_across_runs_of_a_block(spark, monkeypatch, limits):
    # each text has the string in surroundings of its own, and a block's texts are read in several runs
    limit = suffix_dedup.chunked
    monkeypatch.setattr(suffix_dedup, "chunked", lambda t: limit(t, 400))
    rng = np.random.default_rng(5)
    word = lambda: bytes(rng.integers(97, 123, 150, dtype=np.uint8)).decode()
    table = [(i, word() + "the one passage that stands in every text of this table, with other words around it" + word()) for i in range(200)]
    docs = spark.createDataFrame(table, "doc_id long, text string").repartition(3)
    assert sorted((tuple(r) for r in suffix_dedup.suffix_dedup(docs, **limits).collect()), key=str) == brute_dedup(table)


def test_suffix_dedup_frequent_string_in_equal_surroundings_is_not_hot():
    import pyarrow as pa

    def hot_bytes(texts):
        blocks = [pa.table({"block": pa.array([b] * len(texts(b)), pa.int32()), "doc_id": pa.array(range(100 * b, 100 * b + len(texts(b)))), "text": texts(b)}) for b in range(300)]
        rows = pa.concat_tables([suffix_dedup._anchors(50, 1)(t) for t in blocks])
        told = suffix_dedup._shared(None, 1000)(rows)
        return sum(map(len, told["hot"].to_pylist())), sum(map(len, told["shared"].to_pylist()))

    line = "one line of sixty bytes and more that is in all of the texts here"
    assert hot_bytes(lambda b: [line] * 3)[0] == 0 < hot_bytes(lambda b: [line] * 3)[1]
    assert hot_bytes(lambda b: [f"{line}{b:05d}{i:02d}" + "x" * 50 for i in range(20)])[0] > 0


def test_workers_give_back_freed_memory():
    import ctypes
    import pathlib

    from triadspark.llm import textkernel

    if not hasattr(ctypes.CDLL(None), "malloc_trim"):
        pytest.skip("another C library")
    resident = lambda: int(pathlib.Path("/proc/self/statm").read_text().split()[1]) * 4096
    held = [b"x" * (100_000 + i % 2) for i in range(3000)]
    kept = held[::50]
    del held
    before = resident()
    textkernel.release_encoders()
    assert len(kept) == 60 and before - resident() > 100 << 20


def test_encoders_of_a_worker_go_at_once():
    import gc
    import weakref

    from triadspark.llm import encoding, textkernel

    bpe = bpe_sql.sql_bpe(RANKS, public_tokenizers.PATTERN)
    gone = weakref.ref(bpe)
    del bpe
    gc.disable()
    try:
        textkernel.release_encoders()
        assert gone() is None and not [k for k in vars(encoding.worker_state()) if ":" in k]
    finally:
        gc.enable()


def test_bpe_decodes_in_stretches(monkeypatch):
    counts = np.array([0, 3, 4, 0, 9, 1, 1, 0])
    runs = list(bpe_sql._id_runs(counts, 4))
    assert [i for lo, hi in runs for i in range(lo, hi)] == list(range(8))
    assert all(hi - lo == 1 or counts[lo:hi].sum() <= 4 for lo, hi in runs) and not list(bpe_sql._id_runs(counts[:0]))
    seen, decode = [], bpe_sql.SqlBpe.decode
    monkeypatch.setattr(bpe_sql.SqlBpe, "decode", lambda self, ids, counts: (seen.append(len(ids)), decode(self, ids, counts))[1])
    texts = ["some words and one more " * 2500, "", None, "caf\u00e9 " * 200_000, "last"]
    batch = pa.RecordBatch.from_pydict({"doc_id": pa.array(range(5), pa.int64()), "text": pa.array(texts, pa.string())})
    (got,) = (x.to_pylist() for x in bpe_sql._round_trip(RANKS, public_tokenizers.PATTERN, True, 1000, 6 << 20)([batch]))
    assert len(seen) > 1 and [r["decoded"].decode() for r in got] == [t or "" for t in texts]
    for r in got:
        assert r["n_tokens"] == len(r["ids"]) and r["ids_sha256"] == hashlib.sha256(",".join(map(str, r["ids"])).encode()).hexdigest() and r["decoded_sha256"] == hashlib.sha256(r["decoded"]).hexdigest()


def test_quality_counts_take_little_memory():
    import tracemalloc

    text = ["plain words of a long document " * 70] * 2000
    batch = pa.RecordBatch.from_pydict({"doc_id": pa.array(range(2000), pa.int64()), "text": text, "lang": ["en"] * 2000})
    tracemalloc.start()
    assert sum(x.num_rows for x in quality_rules._measured([batch])) == 2000
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 60 << 20


def test_jaccard_signature_rows_are_packed():
    jj = jaccard_join
    rng = np.random.default_rng(3)
    for x in (np.array([-(1 << 63), -5, 0, 7, (1 << 63) - 1]), np.array([4]), np.arange(1000) * 300 - 5000):
        assert (jj._unpacked_ids(jj._packed_ids(x)) == x).all()
    for x in (np.array([3, 255]), np.array([0, 256]), np.array([70_000, 1]), np.array([1 << 33]), np.zeros(0, np.int64)):
        assert (jj._unpacked(jj._packed(x)) == x.astype(np.uint64)).all()
    comp = rng.integers(-3, 1 << 62, 50)[rng.integers(0, 50, 900)]
    assert (jj._unpacked_comps(jj._packed_comps(comp)) == comp).all()
    doc = np.sort(rng.permutation(4000)[:3000])
    own = np.repeat(doc, 240)
    sig, of = rng.integers(0, 1 << 63, len(own)).astype(np.uint64), np.repeat(rng.integers(0, 500, 3000), 240)
    t = pa.Table.from_batches([jj._emit(122, own, of, sig)])
    got_sig, got_doc, counts = jj._bucket(t)
    comps = np.concatenate([np.repeat(jj._unpacked_comps(x), c) for x, c in zip(t["comps"].to_pylist(), counts, strict=True)])
    assert sorted(zip(got_sig.tolist(), got_doc.tolist(), comps.tolist(), strict=True)) == sorted(zip((sig & np.uint64(0xFFFFFFFF)).tolist(), own.tolist(), of.tolist(), strict=True))
    assert t.nbytes < 6.5 * len(sig)  # 4 bytes are the signature's; with whole ids, counts and components it was 14


def test_jaccard_leaves_no_shuffle_files(spark, odd):
    held = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def seen():
        files = held.getAllFiles()
        return {n for n in (files.apply(i).getName() for i in range(files.length())) if n.startswith("shuffle_")}

    before = seen()
    jaccard_join.jaccard_components(odd)
    for _ in range(50):
        if not seen() - before:
            break
        time.sleep(0.1)
    assert not seen() - before
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"


def test_suffix_order_and_prefixes():
    rng = np.random.default_rng(1)
    for _ in range(60):
        t = np.frombuffer(b"\0".join(bytes(rng.integers(1, 4, rng.integers(1, 30)).astype(np.uint8)) for _ in range(5)) + b"\0", np.uint8)
        o, b = suffix_dedup.suffix_order(t, 50), t.tobytes()
        assert sorted(o) == list(range(len(t)))
        assert all(b[x : x + 50] <= b[y : y + 50] for x, y in zip(o, o[1:], strict=False))


def test_jaccard_dense_and_pairwise_ways_agree(spark, odd):
    base = [f"w{i}" for i in range(60)]
    docs = []
    for i in range(40):
        ws = list(base)
        for j in range(i % 5):
            ws[(7 * i + 11 * j) % 60] = f"z{i}_{j}"
        docs.append((i, " ".join(ws)))
    docs += [(100 + i, f"a{i} b c d") for i in range(3)] + [(200, "same four words here"), (201, "Same four words here")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    sets = {d: {tuple(t.lower().split()[k : k + 5]) for k in range(max(1, len(t.split()) - 4))} for d, t in docs}
    comp = {d: d for d in sets}
    for a in sets:
        for b in sets:
            if a < b and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((comp[a], comp[b]))
                comp = {k: x if v == y else v for k, v in comp.items()}
    for small, tile in ((24, 512), (2, 8)):
        got = {r.doc_id: r.component_id for r in jaccard_join.jaccard_components(df, small=small, tile=tile).collect()}
        assert got == comp
    x = {r.doc_id: r for r in jaccard_join.jaccard_components(odd).collect()}
    assert x[1].component_id == x[2].component_id == 1 and x[3].n_shingles == x[4].n_shingles == 0 and x[None].component_id is None


def test_jaccard_links_past_hubs_of_other_sizes(spark):
    docs = []
    for f in range(60):  # shorter variants have the smaller ids and lead the stars; only the middle one links the longest
        ws = [f"f{f}w{i}" for i in range(16)]
        docs += [(10 * f + i, " ".join(x)) for i, x in enumerate((ws[:12], ws[1:13], ws[2:14], ws[:13], ws[1:14], ws[:14], ws))]
    sets = {d: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for d, t in docs}
    comp = {d: d for d in sets}
    for a in sets:
        for b in range(a + 1, a // 10 * 10 + 7):
            if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((comp[a], comp[b]))
                comp = {k: x if v == y else v for k, v in comp.items()}
    assert {r.doc_id: r.component_id for r in jaccard_join.jaccard_components(spark.createDataFrame(docs, "doc_id long, text string")).collect()} == comp


def test_token_file(spark, odd, tmp_path):
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(JSON)
    order = sorted(ODD, key=lambda r: (r[0] is not None, r[0] or 0))
    ids = [tool.encode(t or "", add_special_tokens=False).ids + [2] for _, t in order]
    path = token_file.write_tokens(odd, JSON, str(tmp_path / "t"))
    got = sorted((tuple(r) for r in token_file.read_tokens(spark, path).collect()), key=lambda r: r[1])
    start, want = 0, []
    for (d, _), x in zip(order, ids, strict=True):
        want.append((d, start, len(x), zlib.crc32(np.array(x, "<u4").tobytes())))
        start += len(x)
    assert got == want
    flat = [y for x in ids for y in x]
    at = [0, 5, 77, len(flat) - 1]
    assert {tuple(r) for r in token_file.token_lookup(spark, path, spark.createDataFrame([(a,) for a in at], "position long")).collect()} == {(a, flat[a]) for a in at}
    x = np.random.default_rng(2).integers(0, 1 << 24, 3000).astype(np.uint32)
    c, b, r = token_file.pack_levels(x)
    assert (token_file.unpack_levels(c, b) == x).all() and (token_file.tokens_at(c, b, r, np.arange(3000)) == x).all()


def test_words_beside_other_marks_are_not_encoded_again(monkeypatch):
    from triadspark.llm import encoding

    monkeypatch.setattr(encoding, "worker_state", lambda held=type("held", (), {}): held)
    cache, seen = encoding.library_cache(JSON), []
    many = cache.many
    monkeypatch.setattr(cache, "many", lambda xs: seen.extend(xs) or many(xs))
    word = [f"{a}{b}ed" for a in "abcdefghij" for b in "klmnopqrst"]
    text = "".join(f" {w}{mark}" for mark in (",", ".\n", "!", ")", ";\n", ":") for w in word)
    got = list(token_counts._lengths(JSON)([pa.RecordBatch.from_pydict({"text": [text, None, text]})]))[0]
    assert sum(map(len, seen)) < len(text) / 2  # before: each word once a mark
    assert sum(got["n_docs"].to_pylist()) == 3


def test_matches_are_those_of_the_library():
    from tokenizers import Tokenizer

    from triadspark.llm import encoding, textkernel

    tool, cache = Tokenizer.from_file(JSON), encoding.library_cache(JSON)
    mark = ["'", "'s", "'ll", "'re", "'v", "'T", " '", " ", "  ", "\n", "\r\n", "\t", "\x1c", "\x85", "\xa0", "\u3000", "\u2009", "a", "re", "é", "ǅ", "١", "²", "7", "_", "!", "“", "日本", "한", "\u0301", "😀", "\x00"]
    texts = ["", None, *mark, *(a + b for a in mark for b in mark), *(a + b + c for a in mark[:18] for b in mark[:20] for c in mark[:24]), "".join(mark), "".join(reversed(mark)) * 3]
    column = pa.chunked_array([texts[:50], texts[50:]], pa.string())
    want = [tool.encode(t or "", add_special_tokens=False).ids + [2] for t in texts]
    ids, counts = cache.encode(column, 2)
    assert counts.tolist() == list(map(len, want)) and ids.tolist() == [i for w in want for i in w]
    assert len(cache.splitter.starts(*textkernel.text_bytes(column))) == sum(len(tool.pre_tokenizer.pre_tokenize_str(t or "")) for t in texts)


def test_texts_of_a_tokenizer_with_another_pattern_are_encoded_whole(tmp_path):
    import json

    from tokenizers import Tokenizer

    from triadspark.llm import encoding

    with open(JSON, encoding="utf-8") as f:
        other = json.load(f)
    other["pre_tokenizer"]["add_prefix_space"] = True
    (tmp_path / "other.json").write_text(json.dumps(other), encoding="utf-8")
    tool, texts = Tokenizer.from_file(str(tmp_path / "other.json")), ["one two", "", None, "two\n one", "one two"]
    want = [tool.encode(t or "", add_special_tokens=False).ids for t in texts]
    ids, counts = encoding.library_cache(str(tmp_path / "other.json")).encode(pa.chunked_array([texts], pa.string()))
    assert counts.tolist() == list(map(len, want)) and ids.tolist() == [i for w in want for i in w]


def test_token_counts(spark, sf, plain):
    from tokenizers import Tokenizer

    n = np.array([len(e.ids) for e in Tokenizer.from_file(JSON).encode_batch([t for _, t in plain], add_special_tokens=False)])
    for r in QUERIES["op5_token_counts"](spark, sf).collect():
        assert (r.n_docs, r.docs_from, r.tokens_from, r.truncated_tokens) == ((n == r.n_tokens).sum(), (n >= r.n_tokens).sum(), n[n >= r.n_tokens].sum(), np.minimum(n, r.n_tokens).sum())


def test_bpe(spark, odd):
    import tiktoken

    rank = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    tool = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=rank, special_tokens={})
    h = lambda x: hashlib.sha256(x).hexdigest()
    want = [(d, len(i := tool.encode_ordinary(t or "")), h(",".join(map(str, i)).encode()), h((t or "").encode())) for d, t in ODD]
    assert sorted((tuple(r) for r in bpe_sql.bpe_round_trip(odd, RANKS, public_tokenizers.PATTERN).collect()), key=str) == sorted(want, key=str)


def test_bpe_long_words():
    import tiktoken

    own = bpe_sql.SqlBpe(RANKS, public_tokenizers.PATTERN)
    tool = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=own.rank, special_tokens={})
    rng = np.random.default_rng(5)
    words = [(x * 3000)[:n] for x in (b"x", b"ab", b"aba", b"abcab", b"=", b"=-", "\u00e9\u65e5".encode()) for n in (40, 1800)]
    words += [bytes(rng.integers(lo, hi, n, dtype=np.uint8)) for lo, hi in ((97, 99), (97, 101), (97, 123), (0, 256)) for n in (60, 2500)]
    for w in words:
        assert own.long_word(w).tolist() == tool._encode_single_piece(w)
    # long and short words of one run
    flat, size = own.flat_words([words[1], b"the", words[3], b"qzqzq"])
    assert flat.tolist() == [i for w in (words[1], b"the", words[3], b"qzqzq") for i in tool._encode_single_piece(w)] and len(size) == 4


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def test_quality(odd):
    for r in quality_rules.judge_quality(odd).collect():
        t = next(t for d, t in ODD if d == r.doc_id) or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        c = collections.Counter(zip(w, w[1:], w[2:], strict=False))
        rep = {k + j for k, x in enumerate(zip(w, w[1:], w[2:], strict=False)) if c[x] > 1 for j in range(3)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(rep))
        assert r.base_failed == (len(w) < 50 or 100 * len(rep) > 50 * len(w)) and not (r.base_failed and r.kept)


def test_licenses(odd):
    got = collections.defaultdict(list)
    for r in licenses.scan_licenses(odd).collect():
        got[r.doc_id].append(r)
    for d, t in ODD:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
        at = [k for p in licenses.BASE for k in range(len(w)) if w[k : k + len(p.split())] == p.split()]
        r = got[d][0]
        assert (r.n_words, r.n_base, r.first_word, r.last_word) == (len(w), len(at), min(at, default=None), max(at, default=None))
    assert got[12][0].labels == "mit" and got[8][0].base_labels == "cc-by,reserved" and len(got[8]) == 2


def test_licenses_of_files_with_many_notices(spark):
    notices = [(label, n) for label, n, _ in licenses.TEMPLATES]
    docs = [(0, notices[0][1] + " " + notices[2][1]), (1, " and ".join(n for _, n in notices)), (2, "person files work source code form subject terms " * 50 + notices[2][1])]
    docs += [(10 + i, "apache license version " * 3) for i in range(40)] + [(100 + i, n) for i, (_, n) in enumerate(notices)]
    got = {r.doc_id: set(r.labels.split(",")) - {"gpl", "cc-by", "reserved"} for r in licenses.scan_licenses(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got[0] == {"mit", "apache-2.0"} and got[1] == {x for x, _ in notices} - {"gpl"} and got[2] == {"apache-2.0"}
    assert all(got[100 + i] == {x} - {"gpl"} for i, (x, _) in enumerate(notices)) and got[10] == {""}


def test_sharding(odd):
    got = sharding.byte_shards(odd, shards=4).collect()
    assert len(got) == len(ODD)
    for r in got:
        assert (r["size"], r.text_crc32) in {(len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for d, t in ODD if d == r.doc_id}
    for k in {r.shard for r in got}:
        assert sorted(r.slot for r in got if r.shard == k) == list(range(sum(r.shard == k for r in got)))


def test_decontamination_blocks_and_slop(spark, odd):
    bench = spark.createDataFrame([(1, P1), (2, "rights reserved"), (3, None), (None, "Word word word word word word word word word word word"), (4, "one three two")], "item_id long, text string")
    for size in (1 << 20, 10):
        got = collections.defaultdict(list)
        for r in decontamination.find_items(odd, bench, block_bytes=size).collect():
            got[r.doc_id].append(r)
        assert (got[1][0].n_hit, got[1][0]["items"]) == (13, ["1"]) and (got[8][0].n_hit, got[8][0]["items"]) == (6, ["2"]) and got[11][0].n_hit == 80 and got[3][0].n_hit == 0 and len(got[8]) == 2
    near = {r.doc_id: r["near_items"] for r in decontamination.find_items(odd, bench, slop=2).collect()}
    assert "4" in near[1]


def test_decontamination_proximity_at_the_start_of_a_text(spark, sf):
    bench = spark.createDataFrame([(7, "alpha beta gamma delta omega")], "item_id long, text string")
    texts = {1: "omega alpha beta gamma delta", 2: "alpha beta gamma delta"}  # the rarest word comes first, four places early
    for order in ((1, 2), (2, 1)):
        docs = spark.createDataFrame([(d, texts[d]) for d in order], "doc_id long, text string").coalesce(1)
        assert {r.doc_id: list(r.near_items) for r in decontamination.find_items(docs, bench, slop=5).collect()} == {1: ["7"], 2: []}
    near = {r.doc_id: r for r in QUERIES["op10_proximity"](spark, sf).collect()}
    exact = {r.doc_id: r for r in QUERIES["op10_decontamination"](spark, sf).collect()}
    assert near.keys() == exact.keys() and any(r.n_near_items for r in near.values()) and all(near[d].n_near_items >= exact[d].n_items for d in exact)


def test_lm_scores_prefer_target(spark):
    docs = [(i, "the cat sat on the mat and the dog sat too " * 3) for i in range(20)] + [(50 + i, "zz qq zz qq xx zz qq " * 4) for i in range(20)] + [(90, None), (91, "")]
    got = {r.doc_id: r for r in lm_scores.cross_entropy_difference(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(i, 1) for i in range(10)], "doc_id long, quality int")).collect()}
    assert len(got) == len(docs) and got[0].score < got[15].score + 1e-9 < got[50].score and got[90].score is None


def test_lm_scores_of_all_words(spark):
    # 12,000 words, most of them rare: halves of documents differ in rare words only
    docs = [(i, " ".join(f"common w{j}" for j in range(600 * i, 600 * i + 600)) + " common") for i in range(20)]
    docs += [(20 + i, docs[i][1]) for i in range(20)] + [(50, f"common w{11999} common"), (51, "common w0 common"), (60, None), (None, "W0 common w11999")]
    good = set(range(10))
    grams = lambda t: re.findall(r"[a-z0-9]+", (t or "").lower())
    models = []
    for some in ([t for d, t in docs if d in good], [t for _, t in docs]):
        uni, ctx, two = collections.Counter(), collections.Counter(), collections.Counter()
        for w in map(grams, some):
            uni.update(w)
            ctx.update(w + ["<s>"] * bool(w))
            two.update(zip(["<s>"] + w, w))
        models.append((uni, ctx, two))
    v = len(models[1][0])
    assert v == 12001
    want = {}
    for d, t in docs:
        w, loss = grams(t), []
        for uni, ctx, two in models:
            p1 = [(uni[x] + 0.1) / (uni.total() + 0.1 * v) for x in w]
            p2 = [two[y, x] / ctx[y] if ctx[y] else q for y, x, q in zip(["<s>"] + w, w, p1)]
            loss.append(-sum(np.log(0.7 * a + 0.3 * b) for a, b in zip(p2, p1)) / len(w) if w else None)
        want[d] = (len(w), *loss)
    table = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    for block, cells in ((50_000, 256), (20_000, 3)):  # with 3 cells a block, counts are added in several rounds
        got = lm_scores.cross_entropy_difference(table, spark.createDataFrame([(d, 1) for d in good], "doc_id long, quality int"), block_bytes=block, cells=cells).collect()
        assert len(got) == len(docs)
        for r in got:
            assert r.n_tokens == want[r.doc_id][0] and (r.target_loss, r.background_loss) == pytest.approx(want[r.doc_id][1:], abs=2e-6)


def test_lm_scores_of_a_whole_table(spark, sf, plain):
    """Plain counting of every word and pair of words."""
    good = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").collect()}
    grams = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
    models = []
    for some in ([t for d, t in plain if d in good], [t for _, t in plain]):
        uni, ctx, two = collections.Counter(), collections.Counter(), collections.Counter()
        for w in map(grams, some):
            uni.update(w)
            ctx.update(w + ["<s> "] * bool(w))
            two.update(zip(["<s> "] + w, w))
        models.append((uni, ctx, two))
    v = len(models[1][0])
    got = {r.doc_id: r for r in QUERIES["op4_lm_scores"](spark, sf).collect()}
    assert len(got) == len(plain)
    for d, t in plain:
        w, loss = grams(t), []
        for uni, ctx, two in models:
            p1 = [(uni[x] + 0.1) / (uni.total() + 0.1 * v) for x in w]
            p2 = [two[y, x] / ctx[y] if ctx[y] else q for y, x, q in zip(["<s> "] + w, w, p1)]
            loss.append(-sum(np.log(0.7 * a + 0.3 * b) for a, b in zip(p2, p1)) / len(w) if w else None)
        assert got[d].n_tokens == len(w)
        if w:
            assert (got[d].target_loss, got[d].background_loss, got[d].score) == pytest.approx((*loss, loss[0] - loss[1]), abs=3e-6)


def test_lm_counts_beyond_32_bits():
    import pyarrow as pa

    key = np.array([1, 2, 5], np.uint64)
    rows = [lm_scores._cut_rows(key, np.array([0, 7, 1 << 40]), np.array([3_000_000_000, 1 << 33, 1 << 50]), 0, 1, 1, b) for b in range(3)]
    t = lm_scores._total(pa.concat_tables(rows))
    for b in range(3):
        assert lm_scores._unpack(t["back"][b].as_py()).tolist() == [9_000_000_000, 3 << 33, 3 << 50] and lm_scores._unpack(t["target"][b].as_py()).tolist() == [0, 21, 3 << 40]


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string, lang string")
    bench = spark.createDataFrame([], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    for f in (suffix_dedup.suffix_dedup, jaccard_join.jaccard_components, quality_rules.judge_quality, licenses.scan_licenses, sharding.byte_shards,
              lambda d: decontamination.find_items(d, bench), lambda d: lm_scores.cross_entropy_difference(d, labels), lambda d: token_counts.context_answers(token_counts.length_histogram(d, JSON)), lambda d: bpe_sql.bpe_round_trip(d, RANKS, public_tokenizers.PATTERN)):
        assert f(none).count() == 0


def brute_quality(table):
    """(kept, both distances) of every (doc_id, text, lang), byte by byte and word by word."""
    import math

    marks = b".,;:!?'\"()-"
    kind = lambda x: 0 if 97 <= x <= 122 else 1 if 65 <= x <= 90 else 2 if 48 <= x <= 57 else 3 if x == 32 or 9 <= x <= 13 else 4 if x in marks else 5 if x in b"#*$%&|<>" else 7 if x >= 128 else 6
    every = [w for ws in quality_rules.COMMON.values() for w in ws[:5]]
    seen, sums = [], {}
    for _, t, lang in table:
        raw = (t or "").encode()
        w = re.findall(rb"[^\x20\x09-\x0D]+", raw)
        c = collections.Counter(zip(w, w[1:], w[2:], strict=False))
        rep = {k + j for k, x in enumerate(zip(w, w[1:], w[2:], strict=False)) if c[x] > 1 for j in range(3)}
        failed = len(w) < 50 or 100 * len(rep) > 50 * len(w)
        common = quality_rules.COMMON.get(lang, every)
        low = re.sub(rb"[A-Z]", lambda m: m[0].lower(), raw)
        hist = collections.Counter(map(kind, raw)), collections.Counter(x.decode() if x.decode(errors="replace") in common else "" for x in re.findall(rb"[a-z\x80-\xff]+", low))
        key = lang if lang in quality_rules.COMMON else None
        seen.append((len(w), sum(len(x.decode()) for x in w), failed, key, hist))
        if not failed:
            for k in range(2):
                sums.setdefault((key, k), collections.Counter()).update(hist[k])

    def js(p, q):
        p, q = ({k: v / max(x.total(), 1) for k, v in x.items()} for x in (p, q))
        m = {k: (p.get(k, 0) + q.get(k, 0)) / 2 for k in p.keys() | q.keys()}
        return math.sqrt(max(sum(v * math.log2(v / m[k]) for x in (p, q) for k, v in x.items() if v) / 2, 0))

    out = []
    for n, chars, failed, key, hist in seen:
        d = [js(hist[k], sums[key, k]) if (key, k) in sums else 0.0 for k in range(2)]
        out.append((not failed and not (n >= 60 and chars >= 300 and (d[0] > 0.33 or d[1] > 0.42)), *d))
    return out


def test_quality_verdicts_of_a_whole_table(spark, sf):
    table = [(r.doc_id, r.text, r.lang) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = {r.doc_id: r for r in QUERIES["op3_quality_rules"](spark, sf).collect()}
    for (d, _, _), (kept, *dist) in zip(table, brute_quality(table), strict=True):
        assert (got[d].js_chars, got[d].js_words) == pytest.approx(dist, abs=2e-6) and got[d].kept == kept


def test_license_labels_of_a_whole_table(spark, sf, plain):
    import math

    lex = licenses.lexicon()
    split = {d: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t)) for d, t in plain}
    df = collections.Counter(x for w in split.values() for x in set(w) & set(lex))
    idf = {w: math.log((len(split) + 1) / (df[w] + 1)) + 1e-6 for w in lex}
    got = {r.doc_id: r for r in QUERIES["op7_license_scan"](spark, sf).collect()}
    for d, w in split.items():
        labels, best = set(), 0.0
        for phrase, label in licenses.BASE.items():
            p = phrase.split()
            if any(w[k : k + len(p)] == p for k in range(len(w))):
                labels.add(label)
                best = max(best, 0.5)
        for label, notice, keys in licenses.TEMPLATES:
            ws = notice.split()
            for shift in range(-len(ws), len(w)):
                right = [0 <= shift + j < len(w) and w[shift + j] == x for j, x in enumerate(ws)]
                if sum(right) < 2:
                    continue
                at = [next(i for i in range(len(ws)) if ws[i : i + len(k.split())] == k.split()) for k in keys]
                if all(right[i + j] for i, k in zip(at, keys, strict=True) for j in range(len(k.split()))):
                    share = sum(idf.get(x, 0) for x, ok in zip(ws, right, strict=True) if ok) / sum(idf.get(x, 0) for x in ws)
                    if share >= 0.6:
                        labels.add(label)
                        best = max(best, share)
        assert got[d].labels == ",".join(sorted(labels)) and got[d].score == pytest.approx(min(1.0, best), abs=2e-6)


def test_shards_obey_their_law(spark, sf):
    got = sharding.byte_shards(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    total, largest = sum(r["size"] for r in got), max(r["size"] for r in got)
    order = [r.shard for r in sorted(got, key=lambda r: r.doc_id)]
    assert order == sorted(order)
    for k in range(40):
        assert abs(sum(r["size"] for r in got if r.shard == k) - total / 40) <= largest
        assert [r.slot for r in sorted((r for r in got if r.shard == k), key=lambda r: r.doc_id)] == list(range(order.count(k)))


def test_pipeline_against_brute_force(spark, sf, tmp_path):
    import tiktoken

    import corpus_pipeline

    table = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").collect()]
    good = [x for x, v in zip(table, brute_quality([x[:3] for x in table]), strict=True) if v[0]]
    # a second text of one doc_id, a null one, and a repeated row: clean rows stay, one of equal rows does
    a, b = good[0], good[1]
    extra = [(a[0], b[1] + " and some further words of another text", *a[2:]), (None, " ".join(reversed(good[2][1].split())), *good[2][2:]), b, (9_000_001, None, *a[2:]), (9_000_002, "", *a[2:])]
    table += extra
    spark.createDataFrame(table, "doc_id long, text string, lang string, source string, n_chars long").withColumn("block", F_lit("x")).repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = [x for x, v in zip(table, brute_quality([x[:3] for x in table]), strict=True) if v[0]]
    grams = lambda t: {tuple(w[k : k + 5]) for w in [re.findall(r"[^\x20\x09-\x0D]+", lower(t))] for k in range(max(1, len(w) - 4)) if w}
    sets = collections.defaultdict(list)
    for x in rows:
        if x[0] is not None:
            sets[x[0]].append(grams(x[1]))
    comp = {d: d for d in sets}
    for p in sets:
        for q in sets:
            if p < q and comp[p] != comp[q] and any(100 * len(s & t) >= 80 * len(s | t) for s in sets[p] for t in sets[q]):
                lo, hi = sorted((comp[p], comp[q]))
                comp = {k: lo if v == hi else v for k, v in comp.items()}
    rows = list(dict.fromkeys(x for x in rows if x[0] is None or comp[x[0]] == x[0]))
    first = {}
    rank = lambda d: (1 << 63) - 1 if d is None else d
    raws = [(d, t.encode()) for d, t, *_ in rows]
    for d, r in raws:
        for i in range(len(r) - 49):
            first[r[i : i + 50]] = min(first.get(r[i : i + 50], 1 << 63), rank(d))
    left = []
    for d, r in raws:
        gone = bytearray(len(r))
        for i in range(len(r) - 49):
            if first[r[i : i + 50]] < rank(d):
                gone[i : i + 50] = b"\1" * 50
        if sum(gone) < len(r) or not r:
            left.append((d, bytes(x for x, y in zip(r, gone, strict=True) if not y).decode("utf-8", "ignore")))
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
    windows = {tuple(w[k : k + 10]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect() for w in [words(r.text)] if w for k in range(max(1, len(w) - 9))}
    sizes = {len(w) for w in windows}
    clean = [(d, t) for d, t in left for w in [words(t)] if not any(tuple(w[k : k + n]) in windows for n in sizes for k in range(len(w) - n + 1))]
    tool = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks={base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}, special_tokens={})
    h = lambda x: hashlib.sha256(x).hexdigest()
    want = sorted(((d, len(i := tool.encode_ordinary(t)), h(",".join(map(str, i)).encode()), h(t.encode())) for d, t in clean), key=str)
    assert sorted((tuple(r) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()), key=str) == want
    assert sum(d == a[0] for d, _ in clean) in (1, 2) and any(d is None for d, _ in clean)


def test_pipeline_of_an_empty_table(spark, sf, tmp_path):
    import corpus_pipeline

    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_bitmap_of_needed_ids_travels_as_few_rows(spark, monkeypatch):
    from triadspark.llm import common

    sent = []
    monkeypatch.setattr(common.F, "broadcast", lambda d: sent.append(d) or d)
    for n in (None, 20_000):
        got = {r.doc_id for r in common.narrowed(spark.range(100_000).withColumnRenamed("id", "doc_id"), spark.range(0, 100_000, 5).withColumnRenamed("id", "doc_id"), n=n).collect()}
        assert got >= set(range(0, 100_000, 5)) and len(got) < 23_000
        assert sent[-1].count() <= 1024


def test_full_bitmap_is_not_doubled_on_the_driver(spark):
    from pyspark.sql import functions as F

    from triadspark.llm import common

    def sent(plan):
        if plan.nodeName() == "AdaptiveSparkPlan":
            return sent(plan.executedPlan())
        if "QueryStage" in plan.nodeName():
            return sent(plan.plan())
        below = [sent(plan.children().apply(i)) for i in range(plan.children().size())]
        return max([plan.metrics().apply("dataSize").value() if plan.nodeName().startswith("BroadcastExchange") else 0, *below])

    ids = spark.range(0, 1_000_000, 2).withColumnRenamed("id", "doc_id")
    x = common.narrowed(spark.range(1_000_000).withColumnRenamed("id", "doc_id"), ids, words=1 << 18)  # 2 MB of bits
    got = x.agg(F.count("*").alias("c"), F.count_if(F.col("doc_id") % 2 == 0).alias("even"))
    r = got.collect()[0]
    assert r.even == 500_000 and r.c < 520_000
    assert sent(got._jdf.queryExecution().executedPlan()) < 2.2e6

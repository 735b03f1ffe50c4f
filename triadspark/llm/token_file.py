"""Token ids in directly addressable codes.

A file holds segments; a segment holds whole documents.  Ids are cut into 8-bit chunks, lowest first: level 0 has the first chunk of
every id, level 1 the second chunk of those that need one, and so on.  A bitmap per level tells which ids go on, and a
directory holds the number of set bits before every 512, so the place of an id on the next level is one lookup and one
short count: any token is read without decoding those before it.

Files are Parquet tables in the shared folder with one segment a row, in ascending doc_id order (part, seq), in small row groups without block
compression or dictionaries, so bytes are stored as the codes have them; a manifest derives each segment's first token from per-part totals.  A look-up finds the segments
of its positions in the manifest by an equi-join on stretches of positions, and reads those segments alone where they are few.

Edge cases: null text is empty and has only the end id.  A null doc_id sorts first.  Repeated rows each get their own ids; rows of one doc_id
are ordered by text.  An empty table gives an empty file.  Other columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import parts, shared_dir, slim, table
from .encoding import library_cache
from .textkernel import pieces

BLOCK = 512


def pack_levels(ids: np.ndarray) -> tuple[list[bytes], list[bytes], list[bytes]]:
    """(chunks, continuation bitmaps, rank directories), one of each per level."""
    chunks, bits, ranks = [], [], []
    rest = ids.astype(np.uint32)
    while True:
        go_on = rest > 255
        chunks.append(rest.astype(np.uint8).tobytes())
        packed = np.packbits(go_on, bitorder="little")
        bits.append(packed.tobytes())
        words = np.zeros(-(-len(packed) // (BLOCK // 8)) * (BLOCK // 64), "<u8")
        words.view(np.uint8)[: len(packed)] = packed
        per = np.bitwise_count(words).reshape(-1, BLOCK // 64).sum(axis=1, dtype=np.int64)
        ranks.append((np.cumsum(per) - per).astype("<u4").tobytes())
        if not go_on.any():
            return chunks, bits, ranks
        rest = rest[go_on] >> 8


def unpack_levels(chunks: list[bytes], bits: list[bytes]) -> np.ndarray:
    """All ids of a segment."""
    out = np.frombuffer(chunks[0], np.uint8).astype(np.uint32)
    at = np.flatnonzero(np.unpackbits(np.frombuffer(bits[0], np.uint8), count=len(out), bitorder="little").view(bool))
    for level in range(1, len(chunks)):
        out[at] |= np.frombuffer(chunks[level], np.uint8).astype(np.uint32) << np.uint32(8 * level)
        at = at[np.unpackbits(np.frombuffer(bits[level], np.uint8), count=len(at), bitorder="little").view(bool)]
    return out


def tokens_at(chunks: list[bytes], bits: list[bytes], ranks: list[bytes], at: np.ndarray) -> np.ndarray:
    """Ids at the given places of a segment, by rank lookups alone."""
    at = np.asarray(at, np.int64).copy()
    out = np.zeros(len(at), np.uint32)
    live = np.arange(len(at))
    for level in range(len(chunks)):
        c, b, r = np.frombuffer(chunks[level], np.uint8), np.frombuffer(bits[level], np.uint8), np.frombuffer(ranks[level], "<u4")
        place = at[live]
        out[live] |= c[place].astype(np.uint32) << np.uint32(8 * level)
        more = (b[place >> 3] >> (place & 7).astype(np.uint8)) & 1 == 1
        live, place = live[more], place[more]
        if not len(live):
            break
        base = place // BLOCK * (BLOCK // 8)
        whole = np.minimum(base[:, None] + np.arange(BLOCK // 8), len(b) - 1)
        upto = (place[:, None] - base[:, None] * 8) - np.arange(BLOCK // 8) * 8
        mask = ((1 << np.clip(upto, 0, 8)) - 1).astype(np.uint8)
        at[live] = r[place // BLOCK] + np.bitwise_count(b[whole] & mask).sum(axis=1)
    return out


_SEGMENT = "part int, seq int, n_tokens long, doc_ids array<long>, sizes binary, chunks array<binary>, bits array<binary>, ranks array<binary>"


def _encode(path: str, end_id: int | None, segment_bytes: int):
    def run(batches):
        from pyspark import TaskContext

        part, seq = TaskContext.get().partitionId(), 0
        for batch in batches:
            for t in pieces(batch, "text", segment_bytes):
                ids, counts = library_cache(path).encode(t["text"], end_id)
                levels = pack_levels(ids)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([len(ids)], pa.int64()), pa.array([t["doc_id"].to_pylist()], pa.list_(pa.int64())), pa.array([counts.astype("<i8").tobytes()], pa.binary()),
                     *(pa.array([x], pa.list_(pa.binary())) for x in levels)], names=["part", "seq", "n_tokens", "doc_ids", "sizes", "chunks", "bits", "ranks"])
                seq += 1

    return run


def write_tokens(docs: DataFrame, tokenizer: str, path: str, end_id: int | None = 2, part_bytes: int = 8 << 20, segment_bytes: int = 1 << 20) -> str:
    """Encodes all texts and writes the file at `path` (a folder that all executors share)."""
    docs = slim(docs)
    ranged = docs.repartitionByRange(parts(docs, part_bytes), "doc_id").sortWithinPartitions("doc_id", "text")
    coded = ranged.mapInArrow(_encode(tokenizer, end_id, segment_bytes), _SEGMENT)
    coded.write.option("compression", "uncompressed").option("parquet.enable.dictionary", "false").option("parquet.block.size", 1 << 20).option("parquet.page.size", 1 << 18).parquet(path)
    return path


def manifest(spark: SparkSession, path: str) -> DataFrame:
    """(part, seq, base): the first token of each segment, from per-part totals."""
    seg = spark.read.parquet(path).select("part", "seq", "n_tokens")
    total = seg.groupBy("part").agg(F.sum("n_tokens").alias("t"))
    before = total.select("part", (F.sum("t").over(Window.orderBy("part")) - F.col("t")).alias("b"))
    inside = Window.partitionBy("part").orderBy("seq")
    return seg.select("part", "seq", (F.sum("n_tokens").over(inside) - F.col("n_tokens")).alias("i")).join(before, "part").select("part", "seq", (F.col("b") + F.col("i")).alias("base"))


def _digest(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            row = {k: batch[k][i].as_py() for k in ("part", "seq", "doc_ids", "sizes", "chunks", "bits")}
            ids = unpack_levels(row["chunks"], row["bits"]).astype("<u4")
            sizes = np.frombuffer(row["sizes"], "<i8")
            ends = np.cumsum(sizes)
            crc = [zlib.crc32(ids[s:e]) for s, e in zip(ends - sizes, ends, strict=True)]
            n = len(sizes)
            yield pa.RecordBatch.from_arrays([pa.array([row["part"]] * n, pa.int32()), pa.array([row["seq"]] * n, pa.int32()), pa.array(row["doc_ids"], pa.int64()), pa.array(ends - sizes), pa.array(sizes), pa.array(crc, pa.int64())], names=["part", "seq", "doc_id", "rel", "n_tokens", "ids_crc32"])


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the file."""
    seg = spark.read.parquet(path).select("part", "seq", "doc_ids", "sizes", "chunks", "bits")
    each = seg.mapInArrow(_digest, "part int, seq int, doc_id long, rel long, n_tokens long, ids_crc32 long")
    return each.join(manifest(spark, path), ["part", "seq"]).select("doc_id", (F.col("base") + F.col("rel")).alias("start"), "n_tokens", "ids_crc32")


def _pick(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            at = np.array(batch["at"][i].as_py(), np.int64)
            got = tokens_at(*(batch[k][i].as_py() for k in ("chunks", "bits", "ranks")), at - batch["base"][i].as_py())
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(got.astype(np.int64))], names=["position", "id"])


def token_lookup(spark: SparkSession, path: str, positions: DataFrame, stretch: int = 1 << 18, few: int = 2000) -> DataFrame:
    """(position, id) for global token positions (column position).  Positions meet the manifest by stretches of `stretch` tokens; up to `few`
    segments are named in the scan's filter, so that only their row groups are read; more are joined."""
    length = spark.read.parquet(path).select("part", "seq", "n_tokens")
    spans = manifest(spark, path).join(length, ["part", "seq"]).where("n_tokens > 0")
    spans = spans.withColumn("s", F.explode(F.sequence(F.floor(F.col("base") / stretch), F.floor((F.col("base") + F.col("n_tokens") - 1) / stretch))))
    want = positions.select(F.col("position").cast("long").alias("position")).where("position >= 0").withColumn("s", F.floor(F.col("position") / stretch))
    hit = spans.join(want, "s").where("position >= base and position < base + n_tokens").groupBy("part", "seq", "base").agg(F.collect_list("position").alias("at"))
    seg = spark.read.parquet(path).select("part", "seq", "chunks", "bits", "ranks")
    named = hit.select("part", "seq").limit(few + 1).collect()  # a bounded list
    if len(named) <= few:
        parts_of: dict[int, list[int]] = {}
        for r in named:
            parts_of.setdefault(r.part, []).append(r.seq)
        wanted = F.lit(False)
        for p, seqs in sorted(parts_of.items()):
            wanted = wanted | ((F.col("part") == p) & F.col("seq").isin(seqs))
        seg = seg.where(wanted)
    return seg.join(hit, ["part", "seq"]).select("base", "at", "chunks", "bits", "ranks").mapInArrow(_pick, "position long, id long")


def op1_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    write_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), path)
    return read_tokens(spark, path)


QUERIES = {"op1_token_file": op1_token_file}

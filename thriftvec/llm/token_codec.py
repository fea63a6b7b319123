"""Token ids in binary files: canonical length-limited Huffman codes with table-driven decoding.

Counts of all ids give one code of at most 16 bits per id; canonical order makes the code lengths alone describe it.
Files hold independent blocks in ascending doc_id order. A block names its documents' lengths and holds the bit
offset of every `STEP`-th token, so that decoding advances all of them in lock-step through one 65,536-entry table.

At 100 TB: texts are tokenized and their ids counted in one pass; ids of two bytes are written once and shuffled once, by ranges of doc_id; what
reaches the driver is one count per vocabulary entry, which the vocabulary bounds. File totals are summed by a window over one row per file.

File: blocks, each followed by one line feed. Block (little-endian): magic, then unsigned 32-bit numbers: bytes of
the block, segments, tokens, checkpoints, payload bytes; per segment: doc_id (signed 64), tokens (unsigned 32), flags
(unsigned 32; 1: continues the document before it, 2: doc_id is null); checkpoints (unsigned 32 bit offsets);
payload, most significant bit first. Code lengths are kept beside the files as `code.parquet` (id, length).
"""

from __future__ import annotations

import heapq
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_folder, stored
from .tokens import default_path, encoder
from .words import blocks

LIMIT = 16
STEP = 64
BLOCK_TOKENS = 1 << 16
FILE_TOKENS = 4 << 20
MAGIC = b"THB1"
HEAD, HEAD_SIZE = "<4sIIIII", 24


def code_lengths(counts: dict[int, int], limit: int = LIMIT) -> dict[int, int]:
    """Optimal code lengths of at most `limit` bits (package-merge); a single id gets one bit."""
    items = sorted((c, s) for s, c in counts.items() if c > 0)
    if len(items) <= 1:
        return {s: 1 for _, s in items}
    if len(items) > 1 << limit:
        raise ValueError("more ids than codes")
    weights = [c for c, _ in items]
    kinds: list[list[bool]] = []
    merged = weights
    for _ in range(limit - 1):
        pairs = [merged[i] + merged[i + 1] for i in range(0, len(merged) - 1, 2)]
        tagged = list(heapq.merge(((w, 0) for w in weights), ((w, 1) for w in pairs)))
        kinds.append([t == 1 for _, t in tagged])
        merged = [w for w, _ in tagged]
    lengths = [0] * len(weights)
    take = 2 * len(weights) - 2
    for kind in reversed(kinds):
        packages = sum(kind[:take])
        for i in range(take - packages):
            lengths[i] += 1
        take = 2 * packages
    for i in range(take):
        lengths[i] += 1
    return {s: n for (_, s), n in zip(items, lengths, strict=True)}


def canonical(lengths: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Arrays by id: code and length (0: the id has none)."""
    size = max(lengths, default=0) + 1
    code, bits = np.zeros(size, np.uint64), np.zeros(size, np.uint64)
    at = last = 0
    for n, s in sorted((n, s) for s, n in lengths.items()):
        at <<= n - last
        code[s], bits[s], last = at, n, n
        at += 1
    return code, bits


def decode_table(lengths: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """For each 16-bit look-ahead the id and the length of its code."""
    code, bits = canonical(lengths)
    sym, width = np.zeros(1 << LIMIT, np.uint32), np.ones(1 << LIMIT, np.uint8)
    for s, n in lengths.items():
        a = int(code[s]) << (LIMIT - n)
        sym[a : a + (1 << (LIMIT - n))] = s
        width[a : a + (1 << (LIMIT - n))] = n
    return sym, width


def pack_bits(ids: np.ndarray, code: np.ndarray, bits: np.ndarray) -> tuple[bytes, np.ndarray]:
    """Payload and the bit offset of every STEP-th id."""
    n = bits[ids]
    end = np.cumsum(n)
    start = end - n
    total = int(end[-1]) if len(end) else 0
    words = np.zeros((total + 63) // 32 + 1, np.uint64)
    if len(ids):
        value = code[ids] << (np.uint64(64) - (start & np.uint64(31)) - n)
        word = (start >> np.uint64(5)).astype(np.int64)
        first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
        words[word[first]] += np.add.reduceat(value >> np.uint64(32), first)
        words[word[first] + 1] += np.add.reduceat(value & np.uint64(0xFFFFFFFF), first)
    return words.astype(">u4").tobytes()[: (total + 7) // 8], start[::STEP].astype("<u4")


def unpack_bits(parts: list[tuple[bytes, np.ndarray, int]], table: tuple[np.ndarray, np.ndarray]) -> list[np.ndarray]:
    """ids of several (payload, checkpoints, tokens) at once."""
    sym, width = table
    data = np.frombuffer(b"".join(p + b"\0\0\0\0" for p, _, _ in parts), np.uint8)
    base = np.cumsum([0, *(len(p) + 4 for p, _, _ in parts)])[:-1] * 8
    pos = np.concatenate([np.empty(0, np.int64), *(b + c.astype(np.int64) for b, (_, c, _) in zip(base, parts, strict=True))])
    size = np.concatenate([np.empty(0, np.int64), *(np.minimum(STEP, n - np.arange(len(c)) * STEP) for _, c, n in parts)])
    out = np.zeros((len(pos), STEP), np.uint32)
    last = len(data) - 4
    for i in range(STEP):
        at = np.minimum(pos >> 3, max(last, 0))
        look = (data[at].astype(np.uint32) << 16) | (data[at + 1].astype(np.uint32) << 8) | data[at + 2]
        look = (look >> (8 - (pos & 7)).astype(np.uint32)) & 0xFFFF
        out[:, i] = sym[look]
        pos = pos + np.where(i < size, width[look], 0)
    res, a = [], 0
    for _, c, n in parts:
        res.append(out[a : a + len(c)].reshape(-1)[:n])
        a += len(c)
    return res


def _narrow(path: str):
    """Texts -> ids as bytes, two for each id where the vocabulary allows it; a task's last row has the counts of its ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        kind = "<u2" if len(enc.edge) <= 1 << 16 else "<u4"
        total = np.zeros(len(enc.edge), "<i8")

        def out(doc_ids: pa.Array, ids: list[bytes], counts: list[bytes]) -> pa.RecordBatch:
            some = pa.array([None] * (len(ids) - len(counts)) + counts, pa.binary())
            return pa.RecordBatch.from_arrays([doc_ids, pa.array(ids, pa.binary()), some], names=["doc_id", "ids", "counts"])

        held = None
        for b in blocks(batches, "text"):
            if held:
                yield out(*held, [])
            wide = [np.frombuffer(x + b"\0\0\0\0", "<u4") for x in enc.encode(b.column("text").to_pylist())]
            total += np.bincount(np.concatenate(wide), minlength=len(total))
            held = b.column("doc_id"), [x.astype(kind).tobytes() for x in wide]
        if held:
            yield out(*held, [total.tobytes()])

    return run


def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.int64(0)
    for b in batches:
        for x in b.column("counts").to_pylist():
            total = total + np.frombuffer(x, "<i8")
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at] if len(at) else [], pa.int64())], names=["id", "c"])


def _blocks(kind: str, lengths: dict[int, int]):
    schema = pa.schema([("block", pa.binary())])

    def make(segments: list[tuple[int, int, int]], ids: np.ndarray, code: np.ndarray, bits: np.ndarray) -> bytes:
        payload, marks = pack_bits(ids, code, bits)
        body = b"".join(struct.pack("<qII", *s) for s in segments) + marks.tobytes() + payload
        return struct.pack(HEAD, MAGIC, HEAD_SIZE + len(body), len(segments), len(ids), len(marks), len(payload)) + body

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, bits = canonical(lengths)
        segments: list[tuple[int, int, int]] = []
        held: list[np.ndarray] = []
        n = 0
        for b in blocks(batches, "ids"):
            made = []
            for d, x in zip(b.column("doc_id").to_pylist(), b.column("ids").to_pylist(), strict=True):
                ids = np.frombuffer(x, kind)
                a = 0
                while a < len(ids):
                    part = ids[a : a + BLOCK_TOKENS - n]
                    segments.append((d or 0, len(part), (a > 0) + 2 * (d is None)))
                    held.append(part)
                    n += len(part)
                    a += len(part)
                    if n == BLOCK_TOKENS:
                        made.append(make(segments, np.concatenate(held), code, bits))
                        segments, held, n = [], [], 0
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], schema=schema)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([make(segments, np.concatenate(held), code, bits)], pa.binary())], schema=schema)

    return run


def write_tokens(docs: DataFrame, folder: str, vocabulary: str | None = None) -> None:
    """Write the ids of docs(doc_id, text), each document closed by id 0, in ascending doc_id order under `folder`.

    Null and empty texts are the closing id alone; null doc_ids come first; repeated rows are written one after
    another. An empty table writes no block. Other columns are ignored.
    """
    spark = docs.sparkSession
    path = vocabulary or default_path("byte_bpe_50k.json")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    ids = stored(docs.mapInArrow(_narrow(path), "doc_id long, ids binary, counts binary"))
    kind = "<u2" if len(encoder(path).edge) <= 1 << 16 else "<u4"
    counts = {r["id"]: r["c"] for r in ids.select("counts").where("counts is not null").mapInArrow(_add, "id long, c long").groupBy("id").agg(F.sum("c").alias("c")).collect()}
    lengths = code_lengths(counts)
    spark.createDataFrame([(int(s), int(n)) for s, n in lengths.items()], "id long, length int").coalesce(1).write.parquet(f"{folder}/code.parquet")
    files = max(1, -(-sum(counts.values()) // FILE_TOKENS))
    ordered = ids.select("doc_id", "ids").repartitionByRange(files, "doc_id").sortWithinPartitions("doc_id")
    made = ordered.mapInArrow(_blocks(kind, lengths), "block binary")
    # the text writer puts a string's bytes out as they are, one line feed after each
    made.select(F.col("block").cast("string").alias("value")).write.option("compression", "none").text(f"{folder}/blocks")


def _read(lengths: dict[int, int], with_ids: bool):
    names = ["path", "place", "null_id", "doc_id", "start", "n_tokens", "ids_crc32"] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = decode_table(lengths)
        for b in batches:
            for path, content in zip(b.column("path").to_pylist(), b.column("content"), strict=True):
                data = memoryview(content.as_buffer())
                at, rows, heads, parts = 0, [], [], []
                start = 0

                def flush():
                    nonlocal start
                    for segs, ids in zip(heads, unpack_bits(parts, table), strict=True):
                        a = 0
                        for d, n, flags in segs:
                            raw = ids[a : a + n].astype("<u4").tobytes()
                            a += n
                            if flags & 1 and rows:
                                rows[-1][4] += n
                                rows[-1][5] = zlib.crc32(raw, rows[-1][5])
                                if with_ids:
                                    rows[-1][6] += raw
                            else:
                                rows.append([len(rows), bool(flags & 2), d, start, n, zlib.crc32(raw), *([raw] if with_ids else [])])
                            start += n
                    heads.clear()
                    parts.clear()

                while at < len(data):
                    magic, size, segments, tokens, marks, payload = struct.unpack_from(HEAD, data, at)
                    if magic != MAGIC:
                        raise ValueError(f"{path}: no block at byte {at}")
                    p = at + HEAD_SIZE
                    heads.append([struct.unpack_from("<qII", data, p + 16 * i) for i in range(segments)])
                    p += 16 * segments
                    parts.append((bytes(data[p + 4 * marks : p + 4 * marks + payload]), np.frombuffer(data, "<u4", marks, p), tokens))
                    at += size + 1
                    if len(parts) == 8:
                        flush()
                flush()
                if rows:
                    cols = list(zip(*rows, strict=True))
                    arrays = [pa.array([path] * len(rows)), pa.array(cols[0], pa.int64()), pa.array(cols[1]), pa.array([None if z else d for d, z in zip(cols[2], cols[1], strict=True)], pa.int64()), *(pa.array(c, pa.int64()) for c in cols[3:6])]
                    yield pa.RecordBatch.from_arrays([*arrays, *([pa.array(cols[6], pa.binary())] if with_ids else [])], names=names)

    return run


def read_tokens(spark, folder: str, with_ids: bool = False) -> DataFrame:
    """Files of write_tokens -> doc_id, start (ids of all documents before it), n_tokens, ids_crc32 (and ids)."""
    lengths = {r["id"]: r["length"] for r in spark.read.schema("id long, length int").parquet(f"{folder}/code.parquet").collect()}
    files = spark.read.format("binaryFile").load(f"{folder}/blocks").where("length > 0").select("path", "content")
    schema = "path string, place long, null_id boolean, doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids
    rows = stored(files.mapInArrow(_read(lengths, with_ids), schema))
    totals = rows.groupBy("path").agg(F.sum("n_tokens").alias("n"), F.min("doc_id").alias("low"), F.max(F.col("null_id")).alias("nulls"))
    before = Window.orderBy(F.desc("nulls"), "low", "path").rowsBetween(Window.unboundedPreceding, -1)
    starts = totals.select("path", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    out = rows.join(starts, "path").withColumn("start", F.col("start") + F.col("before"))
    return out.select("doc_id", "start", "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))


def round_trip(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    folder = shared_folder(docs.sparkSession)
    write_tokens(docs, folder, vocabulary)
    return read_tokens(docs.sparkSession, folder)

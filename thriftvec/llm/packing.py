"""Bound-certified repacking of documents into sequences of at most `capacity` tokens.

Pieces are dealt by hash to buckets of bounded size; each bucket is packed by best-fit decreasing, and a set of
dual-feasible functions gives a lower bound of its number of bins. A bucket that meets its bound is certified; the
others hand their emptiest bins back. Handed-back pieces are dealt anew, so that buckets exchange documents, and best-fit
decreasing runs again, until every bucket is certified or one bucket is left. Half-empty bins always travel on: they
meet those of other buckets.

At 100 TB: one shuffle of piece rows (ids and lengths only) for the first round and much smaller ones afterwards.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored
from .tokens import default_path, encoder
from .words import blocks

CAPACITY = 2048
BUCKET = 2048  # pieces that one bucket packs


def _pieces(path: str, capacity: int, with_ids: bool, keys: list[str], schema: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for b in blocks(batches, "text"):
            row, piece, start, length, crc, ids = [], [], [], [], [], []
            for r, x in enumerate(enc.encode(b.column("text").to_pylist())):
                x += b"\0\0\0\0"
                for p, a in enumerate(range(0, len(x), 4 * capacity)):
                    part = x[a : a + 4 * capacity]
                    row.append(r)
                    piece.append(p)
                    start.append(a // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
                    ids.append(part if with_ids else None)
            take = pa.array(row, pa.int64())
            cols = [b.column(k).take(take) for k in keys]
            made = [pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
            yield pa.RecordBatch.from_arrays([*cols, *made, *([pa.array(ids, pa.binary())] if with_ids else [])], schema=schema)

    return run


def lower_bound(lengths: np.ndarray, capacity: int = CAPACITY) -> int:
    """Bins that any packing needs: the best of two families of dual-feasible functions over a histogram of lengths."""
    if not len(lengths):
        return 0
    count = np.bincount(lengths, minlength=capacity + 1)[: capacity + 1].astype(np.int64)
    size = np.arange(capacity + 1, dtype=np.int64)
    total = int((count * size).sum())
    best = -(-total // capacity)
    many, mass = np.cumsum(count), np.cumsum(count * size)
    lam = np.arange(1, capacity // 2 + 1)
    # lengths above capacity - lam count as whole bins, those below lam as nothing
    inner = mass[capacity - lam] - mass[lam - 1]
    best = max(best, int((-(-(inner + (many[-1] - many[capacity - lam]) * capacity) // capacity)).max()))
    for k in range(1, 33):
        scaled = (k + 1) * size
        whole = scaled % capacity == 0
        # in units of 1 / (k * capacity) of a bin
        value = np.where(whole, k * size, scaled // capacity * capacity)
        best = max(best, -(-int((count * value).sum()) // (k * capacity)))
    return best


def best_fit_decreasing(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each piece; each goes, longest first, to the fullest bin that takes it."""
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    room: list[list[int]] = [[] for _ in range(capacity + 1)]
    there, used = 0, 0  # bit r of `there`: a bin with r free places exists
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        above = there >> n
        if above:
            r = n + (above & -above).bit_length() - 1
            k = room[r].pop()
            if not room[r]:
                there ^= 1 << r
        else:
            r, k = capacity, used
            used += 1
        bins[i], offsets[i] = k, capacity - r
        room[r - n].append(k)
        there |= 1 << (r - n)
    return bins, offsets


def _pack(capacity: int, round_no: int, schema: pa.Schema):
    def run(key, table):
        table = table.sort_by("_uid")
        n = table.column("length").to_numpy()
        bins, offsets = best_fit_decreasing(n, capacity)
        used = int(bins.max()) + 1
        free = capacity - np.bincount(bins, weights=n, minlength=used).astype(np.int64)
        gap = used - lower_bound(n, capacity)
        back = free >= capacity // 2
        if gap:
            worst = np.argsort(-free, kind="stable")
            enough = int(np.searchsorted(np.cumsum(free[worst]), (gap + 1) * capacity)) + 1
            back[worst[:enough]] = True
        sequence = bins + ((round_no << 56) | (key[0].as_py() << 16))  # ids are dealt evenly: a bucket has far fewer than 2^16 pieces
        made = {"sequence_id": pa.array(sequence), "offset": pa.array(offsets), "_back": pa.array(back[bins])}
        return pa.Table.from_arrays([made[f.name] if f.name in made else table.column(f.name) for f in schema], schema=schema)

    return run


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """pieces with a column `length` (1..capacity) -> the same rows with sequence_id and offset.

    Rounds go on until every bucket is certified or one bucket is left. A round that hands back more than nine tenths of
    what it got ends them too: exchange no longer helps then, and its bins stay as they are.
    """
    from pyspark.sql.pandas.types import to_arrow_schema

    cols = pieces.columns
    left = stored(pieces.withColumn("_uid", F.monotonically_increasing_id()))
    whole = left.where(F.col("length") == capacity).select(*cols, F.col("_uid").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    done = [whole]
    left = left.where(F.col("length") < capacity)
    names = left.columns
    schema = left.select(*names, F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"), F.lit(True).alias("_back")).schema
    fields = to_arrow_schema(schema)
    n, round_no = left.count(), 0
    while n:
        round_no += 1
        k = -(-n // BUCKET)
        made = left.withColumn("_bucket", F.pmod(F.xxhash64("_uid", F.lit(round_no)), F.lit(k))).groupBy("_bucket").applyInArrow(_pack(capacity, round_no, fields), schema)
        made = stored(made)
        back = made.where("_back")
        again = 0 if k == 1 else back.count()
        last = not again or 10 * again > 9 * n
        done.append((made if last else made.where("not _back")).select(*cols, "sequence_id", "offset"))
        if last:
            break
        left, n = back.select(*names), again
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def pack_documents(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids with with_ids).

    A document's ids are those of its whole text and a closing 0; only documents longer than `capacity` are cut, into
    whole-capacity pieces and a rest. A null or empty text is one piece of the closing id alone. Repeated rows and null
    doc_ids are packed as rows of their own; other columns are ignored; an empty table gives an empty result.
    """
    path = vocabulary or default_path("word_bpe_49k.json")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    schema = [("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())] + ([("ids", pa.binary())] if with_ids else [])
    pieces = docs.mapInArrow(_pieces(path, capacity, with_ids, ["doc_id"], pa.schema(schema)), "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids)
    return pack_pieces(pieces, capacity)

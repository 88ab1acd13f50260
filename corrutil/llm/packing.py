"""Best-fit packing with certified bin counts.

Documents become token ids, are cut into pieces of at most ``capacity`` and dealt by
hash to partitions of about ``target_tokens``. Each partition is packed by best-fit
decreasing. Dual feasible functions bound from below how many bins its pieces need; if
the bound equals the count, the partition is certified: no packing of it is
better. Partitions with a gap release their bins that are not full, certified ones
their emptiest bin (what rounding up each partition costs).
Released documents are exchanged: whole bins are dealt to fewer, new partitions
and packed again, and each such partition keeps the better of its old and its new bins.
Rounds go on until one partition is left or nothing is released.

Edge cases: a null or empty text is its closing identifier alone (one token); repeated
rows, ties and null ids are packed as separate pieces; an empty table packs to
nothing. Other columns are not read.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import keyed, pieces, texts
from .scratch import discard, written
from .tokens import tokenizer_path, word_ids

CAPACITY = 2048
#: The thresholds and multiples of the dual feasible functions that are tried.
MULTIPLES = range(1, 33)


def lower_bound(lengths: np.ndarray, capacity: int = CAPACITY) -> int:
    """The largest bound of three families of dual feasible functions.

    The total; for each threshold p: pieces above capacity - p count as a bin, those
    below p as nothing; for each k: x -> floor((k + 1) x / capacity) / k, which keeps x
    where (k + 1) x is a multiple of the capacity.
    """
    if not len(lengths):
        return 0
    have = np.bincount(lengths, minlength=capacity + 1)[: capacity + 1].astype(np.int64)
    size = np.arange(capacity + 1, dtype=np.int64)
    best = -(-int((have * size).sum()) // capacity)
    count, total = np.r_[0, np.cumsum(have)], np.r_[0, np.cumsum(have * size)]
    p = np.arange(1, capacity // 2 + 1)
    whole = count[-1] - count[capacity - p + 1]  # sizes above capacity - p
    middle = total[capacity - p + 1] - total[p]  # sizes from p to capacity - p
    best = max(best, int((whole + -(-middle // capacity)).max()))
    for k in MULTIPLES:
        scaled = (k + 1) * size
        units = np.where(scaled % capacity == 0, size * k, (scaled // capacity) * capacity)  # in 1 / (k * capacity)
        best = max(best, -(-int((have * units).sum()) // (k * capacity)))
    return best


def best_fit(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin, offset and, by bin, room left; pieces are taken longest first (ties in the order given).

    Rooms are a bit set, so the tightest bin that still fits a piece is its lowest set bit.
    """
    order = np.argsort(-lengths, kind="stable")
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    with_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms, left = 0, []
    for i, n in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fit = rooms >> n
        if fit:
            room = n + (fit & -fit).bit_length() - 1
            b = with_room[room].pop()
            if not with_room[room]:
                rooms ^= 1 << room
        else:
            room, b = capacity, len(left)
            left.append(capacity)
        bins[i], offsets[i] = b, capacity - room
        left[b] = room - n
        if room > n:
            if not with_room[room - n]:
                rooms |= 1 << (room - n)
            with_room[room - n].append(b)
    return bins, offsets, np.array(left, np.int64)


def _cut(path: str, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, end = word_ids(path), bytes(4)
        for batch in batches:
            for part in pieces(batch, "text", 4 << 20):
                row, piece, start, length, crc = [], [], [], [], []
                for k, t in enumerate(ids(texts(part.column("text")))):
                    t += end
                    for j, a in enumerate(range(0, len(t), 4 * capacity)):
                        body = t[a : a + 4 * capacity]
                        row.append(k)
                        piece.append(j)
                        start.append(a // 4)
                        length.append(len(body) // 4)
                        crc.append(zlib.crc32(body))
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def cut_pieces(docs: DataFrame, *, capacity: int = CAPACITY, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32`` of every document's ids, closed by id 0 and cut at the capacity."""
    id_type = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_cut(tokenizer or tokenizer_path(), capacity), f"doc_id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint")


def _pack(turn: int, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in keyed(batches, "part"):
            lengths = group.column("length").to_numpy()
            part = group.column("part")[0].as_py()
            bins, offsets, left = best_fit(lengths, capacity)
            bound = lower_bound(lengths, capacity)
            ids = (np.int64(turn) << 56) | (np.int64(part) << 28) | bins
            if turn:  # the old bins stay if the new ones are not fewer
                old = group.column("sequence_id").to_numpy()
                names, where = np.unique(old, return_inverse=True)
                if len(names) <= len(left):
                    ids, offsets = old, group.column("offset").to_numpy()
                    bins, left = where, capacity - np.bincount(where, lengths).astype(np.int64)
            gap = len(left) - bound
            free = (left > 0) if gap else (left > 0) & (np.arange(len(left)) == left.argmax())
            keep = [k for k in group.schema.names if k not in ("sequence_id", "offset", "released", "bins", "bound")]
            table = pa.table([group.column(k) for k in keep] + [pa.array(ids, pa.int64()), pa.array(offsets, pa.int64()), pa.array(free[bins], pa.bool_()), pa.array(np.full(len(lengths), len(left)), pa.int64()), pa.array(np.full(len(lengths), bound), pa.int64())], names=[*keep, "sequence_id", "offset", "released", "bins", "bound"])
            yield from table.combine_chunks().to_batches(max_chunksize=50_000)

    return run


def _packed(rows: DataFrame, turn: int, capacity: int) -> DataFrame:
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    base = [f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields if f.name not in ("sequence_id", "offset", "released", "bins", "bound")]
    schema = ", ".join([*base, "sequence_id bigint", "offset bigint", "released boolean", "bins bigint", "bound bigint"])
    return rows.repartition(n, "part").sortWithinPartitions("part", F.desc("length"), "doc_id", "piece").mapInArrow(_pack(turn, capacity), schema)


def pack(rows: DataFrame, *, capacity: int = CAPACITY, target_tokens: int = 8 << 20, max_rounds: int = 8) -> DataFrame:
    """The rows (with ``doc_id, piece, length``; read several times, so written before) and ``sequence_id, offset``.

    Also ``bins, bound``: of the partition that placed the piece last, its bins and their lower bound.
    """
    tokens = rows.agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0]
    parts = max(1, math.ceil(tokens / target_tokens))
    dealt = rows.withColumn("part", F.pmod(F.xxhash64(*(k for k in ("doc_id", "piece", "ids_crc32") if k in rows.columns)), F.lit(parts)))
    now = written(_packed(dealt, 0, capacity), "packed")
    settled = []
    for turn in range(1, max_rounds + 1):
        if parts == 1:
            break
        free = now.agg(F.coalesce(F.sum(F.when(F.col("released"), F.col("length"))), F.lit(0))).first()[0]
        if not free:
            break
        settled.append(now.where(~F.col("released")))
        parts = min(max(1, parts // 4), max(1, math.ceil(free / target_tokens)))
        # Whole bins move, so that the old ones can be kept.
        moved = now.where("released").withColumn("part", F.pmod(F.xxhash64("sequence_id"), F.lit(parts)))
        now = written(_packed(moved, turn, capacity), "packed")
    out = now
    for part in settled:
        out = out.unionByName(part)
    return out.drop("part", "released")


def op2_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    rows = written(cut_pieces(spark.read.parquet(f"{sf_dir}/documents.parquet")), "pieces")
    return pack(rows).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "bins", "bound")

"""Removal of repeated substrings by merging the suffix orders of shards.

A byte is removed if a string of ``LENGTH`` bytes that covers it also starts anywhere else.

*Anchors.* Not all suffixes are kept, only those that start at anchors: the places where
the hash of ``GRAM`` bytes is least within ``WINDOW`` starts (the leftmost of equals). The
anchor of a string is fixed by its first ``WINDOW + GRAM - 1`` bytes, so equal
strings have the same anchor at the same distance, and every comparison can start
there. ``CORE`` bytes from an anchor on belong to every string that it anchors.

*Chunks.* Anchors in a row form chunks that end where a core's hash says so (one in ``CHUNK_ANCHORS``),
so copies of a passage have the same chunks inside. A chunk whose bytes (128-bit hash) occur elsewhere is
repeated as a whole; only one place of it, the least, keeps its anchors, so what follows
sees each repeated text once, however many copies there are. A text that repeats itself in short periods has up to
an anchor for each byte: equal chunks of a task's texts, and equal anchors of a chunk, are one row where they are found,
and the others only leave the spans that they cover.

*Certified anchors.* An anchor's whole reach (first byte of its first string to last byte
of its last) repeated elsewhere proves all its strings repeated. Two hashes of 64
bits, of the core and of the reach, are counted by a partial aggregate; most anchors end
here, repeated or unique.

*Merging.* What is left are edges of repeats: anchors that share their core but not
their whole reach. Each shard (input task) ranks its anchors by what follows the core.
Per core, the shard orders are merged by interleave refinement: all start in one block;
symbols of eight bytes at a time split the blocks that hold more than one anchor, and
the depth of a split is the common prefix of the neighbours it parts. Then the
Burrows-Wheeler step: prepending the byte before each anchor (its transform symbol) is a stable
partition of the merged order, whose common prefixes follow from range minima of the
old ones; no suffix is sorted again. After l steps two neighbours with a common prefix of
``LENGTH`` bytes mark the strings that start l bytes before their anchors as repeated.

A core with more than ``CROWD`` different reaches is not gathered: all strings of its
anchors are counted by their 128-bit hashes instead, which is exact in the same sense.

Edge cases: null and empty texts have nothing to remove; texts shorter than ``LENGTH`` are
kept; a document's rows are told apart by id and text, and rows that repeat both are
each other's repeats; null ids are kept apart by text; empty tables give empty tables.
Other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import bounded_batches, keyed, pieces, raw
from .scratch import discard, release, written

LENGTH, GRAM, WINDOW = 400, 16, 256
CORE = LENGTH - WINDOW + 1
CHUNK_ANCHORS = 4
#: Most different reaches of one core that a task gathers, and rows it merges at once.
CROWD, CHUNK = 20_000, 20_000
#: Bytes of texts that are hashed at once; the low bits of a key hold a place among them.
PART, PLACE_BITS = 1 << 20, 30

_MIX = np.uint64(0x9E3779B97F4A7C15)


class _Powers:
    """Tables of the two prefix hashes: byte values, powers of an odd base, and their inverses."""

    def __init__(self, name: str) -> None:
        word = lambda i: xxhash.xxh64_intdigest(f"{name} {i}".encode(), seed=7)
        self.table = np.array([word(i) for i in range(256)], np.uint64)
        self.base = word("base") | 1
        self.inverse = pow(self.base, -1, 1 << 64)
        self.power, self.undo = np.ones(1, np.uint64), np.ones(1, np.uint64)

    def upto(self, n: int) -> None:
        while len(self.power) < n:
            m = len(self.power)
            with np.errstate(over="ignore"):
                self.power = np.concatenate([self.power, self.power * np.uint64(pow(self.base, m, 1 << 64))])
                self.undo = np.concatenate([self.undo, self.undo * np.uint64(pow(self.inverse, m, 1 << 64))])

    def prefix(self, data: np.ndarray) -> np.ndarray:
        self.upto(len(data) + 1)
        out = np.zeros(len(data) + 1, np.uint64)
        np.multiply(self.table[data], self.power[: len(data)], out=out[1:])
        np.cumsum(out, out=out)
        return out

    def span(self, prefix: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        x = (prefix[stop] - prefix[start]) * self.undo[start]
        x ^= x >> np.uint64(29)
        x *= _MIX
        return x ^ (x >> np.uint64(32))


_HASHES: dict[str, _Powers] = {}


def _hash(name: str) -> _Powers:
    if name not in _HASHES:
        _HASHES[name] = _Powers(name)
    return _HASHES[name]


def anchors(data: np.ndarray, at: np.ndarray) -> dict[str, np.ndarray]:
    """Anchors of texts that lie one after another in ``data``, text k from ``at[k]``.

    ``text`` and, counted in the text: ``place`` of the anchor, ``low`` and ``high``, first and last
    start of the strings it anchors; hashes ``core`` and ``reach``.
    """
    names = ("text", "place", "low", "high", "core", "reach")
    n = len(data)
    if n < LENGTH:
        return {k: np.zeros(0, np.int64) for k in names}
    if n >> PLACE_BITS:
        raise ValueError(f"a text of {n} bytes: places are counted up to {1 << PLACE_BITS}")
    one, two = _hash("one"), _hash("two")
    first = one.prefix(data)
    key = first[GRAM:] - first[:-GRAM]
    key *= one.undo[: len(key)]
    key ^= key >> np.uint64(31)
    key *= _MIX
    low_bits = np.uint64((1 << PLACE_BITS) - 1)
    key &= ~low_bits
    key |= np.arange(len(key), dtype=np.uint64)
    # Least key of each window: prefix minima from block to block and suffix minima back.
    full = -(-len(key) // WINDOW) * WINDOW
    padded = np.full(full + WINDOW, np.iinfo(np.uint64).max, np.uint64)
    padded[: len(key)] = key
    rows = padded.reshape(-1, WINDOW)
    ahead = np.minimum.accumulate(rows, axis=1).ravel()
    back = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    m = n - LENGTH + 1
    least = np.minimum(back[:m], ahead[WINDOW - 1 : WINDOW - 1 + m])
    anchor = (least & low_bits).astype(np.int64)
    cut = np.flatnonzero(anchor[1:] != anchor[:-1]) + 1
    long = np.flatnonzero(np.diff(at) >= LENGTH)
    # Runs of starts with one anchor, cut where texts end.
    starts = np.unique(np.concatenate([cut, at[:-1][long], at[1:][long] - LENGTH + 1]))
    starts = starts[starts < m]
    stops = np.r_[starts[1:], m]
    text = np.searchsorted(at, starts, side="right") - 1
    inside = starts + LENGTH <= at[text + 1]
    starts, stops, text = starts[inside], stops[inside], text[inside]
    place, low, high = anchor[starts], starts, stops - 1
    second = two.prefix(data)
    core = one.span(first, place, place + CORE)
    reach = two.span(second, low, high + LENGTH)
    reach += (((place - low) << 10) + (place - high)).astype(np.uint64) * _MIX
    base = at[text]
    return {"text": text, "place": place - base, "low": low - base, "high": high - base, "core": core.view(np.int64), "reach": reach.view(np.int64)}


def firsts(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row the number of the first row with equal keys, and how many there are."""
    order = np.lexsort(keys)
    new = np.r_[True, np.any([k[order][1:] != k[order][:-1] for k in keys], axis=0)]
    group = np.cumsum(new) - 1
    first, times = np.empty(len(order), np.int64), np.empty(len(order), np.int64)
    first[order], times[order] = order[new][group], np.bincount(group)[group]  # a stable sort: the least of equals
    return first, times


def stretches(rows: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last row of each stretch of rows that follow one another in a text."""
    head = np.flatnonzero(np.r_[True, (np.diff(rows) > 1) | (text[rows[1:]] != text[rows[:-1]])]) if len(rows) else rows
    return rows[head], rows[np.r_[head[1:], len(rows)] - 1] if len(rows) else rows


def _chunk_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each chunk: its two hashes, first and last start of its strings, its anchors, and the places in these texts it stands for.

    Anchors that stand for others of their chunk are ``many``. Rows without hashes are spans, by first and last start, that are repeated as they stand.
    """
    one, two = _hash("one"), _hash("two")
    for batch in batches:
        for part in pieces(batch, "text", PART):
            data, at = raw(part.column("text"))
            with np.errstate(over="ignore"):
                found = anchors(data, at)
                n = len(found["text"])
                if not n:
                    continue
                text, low, high = found["text"], found["low"], found["high"]
                closing = found["core"].view(np.uint64) % np.uint64(CHUNK_ANCHORS) == 0
                head = np.flatnonzero(np.r_[True, (text[1:] != text[:-1]) | closing[:-1]])
                last = np.r_[head[1:], n] - 1
                base = at[text[head]]
                a, b = base + low[head], base + high[last] + LENGTH
                x, y = one.span(one.prefix(data), a, b).view(np.int64), two.span(two.prefix(data), a, b).view(np.int64)
            chunk = np.repeat(np.arange(len(head)), last - head + 1)
            same, times = firsts(x, y)
            mine = same == np.arange(len(head))
            # Equal chunks have equal anchors, so which of them stands for the others changes nothing.
            least, alike = firsts(chunk, found["core"], found["reach"])
            stays = np.flatnonzero((least == np.arange(n)) & mine[chunk])
            settled = [stretches(np.flatnonzero(~mine), text[head]), stretches(np.flatnonzero((alike > 1) & mine[chunk]), text)]
            begin = np.r_[low[head[settled[0][0]]], low[settled[1][0]]]
            end = np.r_[high[last[settled[0][1]]], high[settled[1][1]]]
            owner = np.r_[text[head[mine]], text[head[settled[0][0]]], text[settled[1][0]]]
            rest = len(begin)
            take = pa.array(owner, pa.int64())
            fields = [pa.array(found[k][stays].astype(np.int32), pa.int32()) for k in ("place", "low", "high")] + [pa.array(found[k][stays], pa.int64()) for k in ("core", "reach")] + [pa.array(alike[stays] > 1)]
            edges = np.r_[0, np.cumsum(np.bincount(chunk[stays], minlength=len(head))[mine])]
            members = pa.ListArray.from_arrays(pa.array(np.r_[edges, np.full(rest, edges[-1])].astype(np.int32)), pa.StructArray.from_arrays(fields, ["place", "low", "high", "core", "reach", "many"]))
            blank = pa.nulls(rest, pa.int64())
            hashes = [pa.concat_arrays([pa.array(k[mine]), blank]) for k in (x, y)]
            first, final = np.r_[low[head[mine]], begin], np.r_[high[last[mine]], end]
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id").take(take), part.column("mark").take(take), *hashes, pa.array(first.astype(np.int32)), pa.array(final.astype(np.int32)), pa.array(np.r_[times[mine], np.ones(rest, np.int64)]), members],
                ["doc_id", "mark", "x", "y", "first", "last", "times", "anchors"],
            )


def merge_orders(core: np.ndarray, shard: np.ndarray, right: np.ndarray, width: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One order of all rows by core and what follows it, and each row's common prefix with the one before (-1: another core).

    ``right``: the bytes after the core, plus one, rows padded with zeros; ``width``: how many there are.
    Rows of a shard come in that shard's order; blocks of one row, or of one shard whose
    order is known, are not refined further than their common prefixes need.
    """
    order = np.lexsort((shard, core))
    new = np.r_[True, core[order][1:] != core[order][:-1]]
    common = np.where(new, -1, 0)
    words = right.view(">u8").astype(np.uint64)
    block = np.cumsum(new) - 1
    active = np.flatnonzero(np.bincount(block)[block] > 1)
    for depth in range(words.shape[1]):
        if not len(active):
            break
        rows, b = order[active], block[active]
        symbol = words[rows, depth]
        # A stable refinement of the interleave: within its block each row moves behind the lesser symbols.
        moved = np.lexsort((symbol, b))
        order[active] = rows[moved]
        s, b = symbol[moved], b[moved]
        same = np.r_[False, b[1:] == b[:-1]]
        split = same & np.r_[False, s[1:] != s[:-1]]
        differ = np.r_[np.uint64(0), s[1:] ^ s[:-1]]
        lead = np.zeros(len(s), np.int64)
        if split.any():
            lead[split] = (64 - _bit_length(differ[split])) // 8
        common[active] = np.where(same, np.where(split, 8 * depth + lead, 8 * (depth + 1)), common[active])
        starts = split | ~same
        block[active] = np.cumsum(starts) - 1  # numbers within the active rows are enough
        sizes = np.bincount(block[active])
        active = active[sizes[block[active]] > 1]
    limit = np.minimum(width[order], np.r_[0, width[order][:-1]])
    return order, np.where(common < 0, -1, np.minimum(common, limit))


def _bit_length(x: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x), np.int64)
    x = x.copy()
    for shift in (32, 16, 8, 4, 2, 1):
        big = x >> np.uint64(shift) > 0
        out[big] += shift
        x[big] >>= np.uint64(shift)
    return out + (x > 0)


def repeated_starts(order: np.ndarray, common: np.ndarray, left: np.ndarray, least: np.ndarray, most: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """For l = 0, 1, ...: the rows whose string from l bytes before the anchor is repeated.

    ``left``: the bytes before the anchors, nearest first; ``least`` and ``most``: distances l that a row has.
    """
    rows, lcp = order.copy(), common.copy()
    for step in range(WINDOW):
        if not len(rows):
            return
        need = LENGTH - CORE - step
        ok = (lcp >= need) & (lcp >= 0)
        hit = ok.copy()
        hit[:-1] |= ok[1:]
        found = rows[hit]
        found = found[(least[found] <= step) & (step <= most[found])]
        if len(found):
            yield step, found
        # Prepend the transform symbol: a stable partition of each class.
        head = lcp < 0
        group = np.cumsum(head)
        alive = np.flatnonzero(most[rows] > step)
        if not len(alive):
            return
        symbol = left[rows[alive], step].astype(np.int64)
        klass = group[alive] * 256 + symbol
        moved = np.argsort(klass, kind="stable")
        old, k = alive[moved], klass[moved]
        same = np.r_[False, k[1:] == k[:-1]]
        new = np.full(len(old), -1, np.int64)
        new[same] = _range_min(lcp, np.r_[0, old[:-1]][same] + 1, old[same])
        sizes = np.bincount(np.cumsum(~same) - 1)
        stay = sizes[np.cumsum(~same) - 1] > 1
        rows, lcp = rows[old][stay], new[stay]


def _range_min(values: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Least of values[first..last] for each pair (first <= last)."""
    out = values[last].copy()
    wide = np.flatnonzero(first < last)
    if len(wide):
        levels = [values]
        while (1 << len(levels)) <= len(values):
            v = levels[-1]
            h = 1 << (len(levels) - 1)
            levels.append(np.minimum(v[:-h], v[h:]))
        k = _bit_length((last[wide] - first[wide] + 1).astype(np.uint64)) - 1
        for level in np.unique(k).tolist():
            w = wide[k == level]
            out[w] = np.minimum(levels[level][first[w]], levels[level][last[w] - (1 << level) + 1])
    return out


def _contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What lies left of each wanted anchor (nearest byte first) and right of its core; rows of a batch in the shard's order."""
    for batch in batches:
        for part in pieces(batch, "text", PART):
            data, at = raw(part.column("text"))
            whole = data.tobytes()
            wanted = part.column("wanted")
            flat, edges = wanted.flatten(), wanted.offsets.to_numpy()
            edges = edges - edges[0]
            field = {f: flat.field(f).to_numpy() for f in ("core", "place", "low", "high", "reach")}
            alone, crowd = flat.field("alone").to_numpy(zero_copy_only=False), flat.field("crowd").to_numpy(zero_copy_only=False)
            text = np.repeat(np.arange(part.num_rows), np.diff(edges))
            base = at[:-1][text]
            left = [whole[a:b][::-1] for a, b in zip((base + field["low"]).tolist(), (base + field["place"]).tolist(), strict=True)]
            right = [whole[a:b] for a, b in zip((base + field["place"] + CORE).tolist(), (base + field["high"] + LENGTH).tolist(), strict=True)]
            rank = sorted(range(len(right)), key=lambda i: (field["core"][i], right[i]))
            pick = pa.array(rank, pa.int64())
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(field["core"], pa.int64()).take(pick), part.column("doc_id").take(pa.array(text, pa.int64())).take(pick), part.column("mark").take(pa.array(text, pa.int64())).take(pick),
                    *(pa.array(field[f], pa.int32()).take(pick) for f in ("place", "low", "high")), pa.array(field["reach"], pa.int64()).take(pick), pa.array(alone, pa.bool_()).take(pick), pa.array(crowd, pa.bool_()).take(pick),
                    pa.array(left, pa.binary()).take(pick), pa.array(right, pa.binary()).take(pick),
                ],
                ["core", "doc_id", "mark", "place", "low", "high", "reach", "alone", "crowd", "before", "after"],
            )


def _matrix(column: pa.Array, shift: int) -> tuple[np.ndarray, np.ndarray]:
    data, at = raw(column)
    size = np.diff(at)
    out = np.zeros((len(size), WINDOW), np.uint8)
    if len(data):
        row = np.repeat(np.arange(len(size)), size)
        out[row, np.arange(len(data)) - at[:-1][row]] = data + np.uint8(shift)
    return out, size


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spans of repeated strings of the anchors that are alone with their reach."""
    def solve(held: list[pa.Table]) -> Iterator[pa.RecordBatch]:
        rows = pa.concat_tables(held).combine_chunks()
        core = rows.column("core").to_numpy()
        place, low, high = (rows.column(k).to_numpy().astype(np.int64) for k in ("place", "low", "high"))
        left, _ = _matrix(rows.column("before").combine_chunks(), 0)
        right, width = _matrix(rows.column("after").combine_chunks(), 1)
        alone = rows.column("alone").to_numpy().astype(bool)
        order, common = merge_orders(core, rows.column("shard").to_numpy(), right, width)
        runs: dict[int, list[list[int]]] = {}
        for step, found in repeated_starts(order, common, left, place - high, place - low):
            for i in found[alone[found]].tolist():
                mine = runs.setdefault(i, [])
                if mine and mine[-1][1] == step - 1:
                    mine[-1][1] = step
                else:
                    mine.append([step, step])
        who = [i for i, r in runs.items() for _ in r]
        spans = [(int(place[i]) - b, int(place[i]) - a + LENGTH) for i, r in runs.items() for a, b in r]
        take = pa.array(who, pa.int64())
        table = pa.table([rows.column("doc_id").take(take), rows.column("mark").take(take), pa.array([s for s, _ in spans], pa.int32()), pa.array([e for _, e in spans], pa.int32())], names=["doc_id", "mark", "start", "stop"])
        yield from table.combine_chunks().to_batches()

    held, n = [], 0
    for group in keyed(batches, "core"):
        if n and n + group.num_rows > CHUNK:
            yield from solve(held)
            held, n = [], 0
        held.append(group)
        n += group.num_rows
    if held:
        yield from solve(held)


def _all_strings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Hash of every string of each anchor of a crowded core (the core itself is part of the key)."""
    for batch in batches:
        for a in range(0, batch.num_rows, 256):
            part = batch.slice(a, 256)
            who, steps, digests = [], [], []
            for i, (before, after, place, low, high) in enumerate(zip(*(part.column(k).to_pylist() for k in ("before", "after", "place", "low", "high")), strict=True)):
                for step in range(place - high, place - low + 1):
                    who.append(i)
                    steps.append(step)
                    digests.append(xxhash.xxh3_64_intdigest(before[:step] + b"\xff" + after[: LENGTH - CORE - step]))
            take = pa.array(who, pa.int64())
            yield pa.RecordBatch.from_arrays([*(part.column(k).take(take) for k in ("core", "doc_id", "mark", "place", "alone")), pa.array(steps, pa.int32()), pa.array(np.array(digests, np.uint64).view(np.int64), pa.int64())], ["core", "doc_id", "mark", "place", "alone", "step", "digest"])


def _keyed_docs(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text.alias("text")).withColumn("mark", F.xxhash64("text"))


def repeated_spans(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", crowd: int = CROWD) -> DataFrame:
    """``doc_id, mark, start, stop``: byte spans to remove (they overlap); mark is the hash of the text."""
    spark = docs.sparkSession
    bounded_batches(spark)
    keyed_docs = _keyed_docs(docs, id_col, text_col)
    long = keyed_docs.where(F.octet_length("text") >= LENGTH)
    who = "doc_id bigint, mark bigint"
    chunks = written(long.mapInArrow(_chunk_rows, f"{who}, x bigint, y bigint, first int, last int, times bigint, anchors array<struct<place:int,low:int,high:int,core:bigint,reach:bigint,many:boolean>>"), "chunks")
    settled = chunks.where("x IS NULL").select("doc_id", "mark", F.col("first").alias("start"), (F.col("last") + LENGTH).alias("stop"))
    hashed = chunks.where("x IS NOT NULL")
    # Copies are counted where they are before they are shuffled; the least place of a repeated chunk stands for all.
    again = hashed.groupBy("x", "y").agg(F.sum("times").alias("n"), F.min(F.struct("doc_id", "mark", "first")).alias("least")).where("n > 1").select("x", "y", "least")
    placed = hashed.join(again, ["x", "y"], "left")
    mine = F.col("least").isNull() | F.col("least").eqNullSafe(F.struct("doc_id", "mark", "first"))
    found = written(placed.select("doc_id", "mark", "first", "last", F.col("least").isNotNull().alias("repeated"), F.when(mine, F.col("anchors")).alias("anchors")), "anchors")
    copied = written(settled.unionByName(found.where("repeated").select("doc_id", "mark", F.col("first").alias("start"), (F.col("last") + LENGTH).alias("stop"))), "copied")
    discard(chunks)
    # What stands for more than one place is settled: its own span is among the copied ones.
    each = found.where("anchors IS NOT NULL").select("doc_id", "mark", "repeated", F.explode("anchors").alias("e")).select("doc_id", "mark", (F.col("repeated") | F.col("e.many")).alias("repeated"), "e.*").drop("many")
    cores = each.groupBy("core").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("core")
    shared = written(each.join(cores, "core", "left_semi"), "shared-anchors")
    discard(found)
    # An anchor that is settled stands for more than one place.
    reaches = written(shared.groupBy("core", "reach").agg(F.sum(F.when(F.col("repeated"), 2).otherwise(1)).alias("n"), F.min(F.struct("doc_id", "mark", "place", "low", "high")).alias("at")), "reaches")
    certain = written(shared.join(reaches.where("n > 1").select("core", "reach"), ["core", "reach"], "left_semi").select("doc_id", "mark", F.col("low").alias("start"), (F.col("high") + LENGTH).alias("stop")), "certain")
    discard(shared)
    open_cores = reaches.groupBy("core").agg(F.min("n").alias("least"), F.count(F.lit(1)).alias("kinds")).where("least = 1").select("core", (F.col("kinds") > crowd).alias("crowd"))
    wanted = (
        reaches.join(open_cores, "core")
        .select("at.doc_id", "at.mark", F.struct("core", "at.place", "at.low", "at.high", "reach", (F.col("n") == 1).alias("alone"), "crowd").alias("w"))
        .groupBy("doc_id", "mark")
        .agg(F.collect_list("w").alias("wanted"))
    )
    same = wanted.withColumnRenamed("doc_id", "d").withColumnRenamed("mark", "m")
    asked = long.join(same, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m"))).select("doc_id", "mark", "text", "wanted")
    kinds = "core bigint, doc_id bigint, mark bigint, place int, low int, high int, reach bigint, alone boolean, crowd boolean, before binary, after binary"
    contexts = written(asked.mapInArrow(_contexts, kinds).withColumn("shard", F.spark_partition_id()), "contexts")
    release(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # A row that the table repeats comes here once more with the same reach: one is enough.
    merged = (
        contexts.where("not crowd").dropDuplicates(["core", "reach"]).repartition(parts, "core").sortWithinPartitions("core", "shard", "after")
        .mapInArrow(_merge, f"{who}, start int, stop int")
    )
    strings = written(contexts.where("crowd").mapInArrow(_all_strings, "core bigint, doc_id bigint, mark bigint, place int, alone boolean, step int, digest bigint"), "strings")
    again = strings.groupBy("core", "step", "digest").agg(F.countDistinct(F.struct("doc_id", "mark", "place")).alias("n")).where("n > 1").select("core", "step", "digest")
    crowded = strings.where("alone").join(again, ["core", "step", "digest"], "left_semi").select("doc_id", "mark", (F.col("place") - F.col("step")).alias("start"), (F.col("place") - F.col("step") + LENGTH).alias("stop"))
    return copied.unionByName(certain).unionByName(merged).unionByName(crowded)


def _joined(spans: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs of overlapping or touching (start, stop)."""
    spans = spans[np.lexsort((spans[:, 1], spans[:, 0]))]
    reach = np.maximum.accumulate(spans[:, 1])
    cut = np.flatnonzero(spans[1:, 0] > reach[:-1]) + 1
    return list(zip(spans[np.r_[0, cut], 0].tolist(), reach[np.r_[cut - 1, len(spans) - 1]].tolist(), strict=True))


def _remove(keep: list[str], digest: bool, noted: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, "text", PART):
                data, at = raw(part.column("text"))
                whole = data.tobytes()
                spans = part.column("spans")
                flat, edges, empty = spans.flatten(), spans.offsets.to_numpy(), spans.is_null().to_numpy(zero_copy_only=False)
                edges = edges - edges[0]
                both = np.column_stack([flat.field("start").to_numpy(), flat.field("stop").to_numpy()]).astype(np.int64) if len(flat) else np.zeros((0, 2), np.int64)
                only = flat.field("noted").to_numpy(zero_copy_only=False).astype(bool) if noted else np.zeros(len(flat), bool)
                rows = []
                for i in range(part.num_rows):
                    body = whole[at[i] : at[i + 1]]
                    at_hand = slice(edges[i], edges[i + 1]) if not empty[i] else slice(0)
                    mine, beside = both[at_hand][~only[at_hand]], both[at_hand][only[at_hand]]
                    runs = _joined(mine) if len(mine) else []
                    cuts = [0, *(x for r in runs for x in r), len(body)]
                    left = b"".join(body[a:b] for a, b in zip(cuts[::2], cuts[1::2], strict=True))
                    rows.append((len(body), len(body) - len(left), len(runs), hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "ignore"), left.decode("utf-8", "ignore") if digest else None, sum(b - a for a, b in _joined(beside)) if len(beside) else 0))
                names = ["n_bytes", "n_removed", "n_spans", "kept", "rest", "noted"]
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
                columns = {n: pa.array(c, t) for n, c, t in zip(names, list(zip(*rows, strict=True)) or [[]] * 6, kinds, strict=True)}
                wanted = [*names[:4], *(["rest"] if digest else []), *(["noted"] if noted else [])]
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keep), *(columns[n] for n in wanted)], [*keep, *wanted])

    return run


def remove_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", digest: bool = False, crowd: int = CROWD, words: int | None = None, note_words: int | None = None) -> DataFrame:
    """All columns of ``docs`` but the text, ``n_bytes, n_removed, n_spans`` and ``kept``: the bytes left, as text or, with ``digest``, SHA-256.

    With ``digest`` the text follows with what is left of it. As text, characters that a removed span cuts in two are dropped. With ``words``, repeated
    passages of so many words go too, also those shorter than ``LENGTH``. With ``note_words`` such passages change nothing of this and are counted:
    ``n_passage_bytes``, the bytes of the text that lie in one, removed or not.
    """
    if note_words is not None:
        from .passages import repeated_passages

        # First, so that nothing of it but its spans is there beside the tables of the suffixes.
        noted = repeated_passages(docs, note_words, id_col=id_col, text_col=text_col, settle=True)
    spans = repeated_spans(docs, id_col=id_col, text_col=text_col, crowd=crowd)
    if words is not None:
        from .passages import repeated_passages

        spans = spans.unionByName(repeated_passages(docs, words, id_col=id_col, text_col=text_col))
    if note_words is not None:
        spans = spans.withColumn("noted", F.lit(False)).unionByName(noted.withColumn("noted", F.lit(True)))
    by_doc = spans.groupBy("doc_id", "mark").agg(F.collect_set(F.struct(*(c for c in spans.columns if c not in ("doc_id", "mark")))).alias("spans")).withColumnRenamed("doc_id", "__d").withColumnRenamed("mark", "__m")
    keep = [c for c in docs.columns if c != text_col]
    rows = docs.select(*(F.col(c).alias(f"k_{i}") for i, c in enumerate(keep)), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"), F.col(id_col).cast("bigint").alias("__id")).withColumn("mark", F.xxhash64("text"))
    names = [f"k_{i}" for i in range(len(keep))]
    joined = rows.join(by_doc, F.col("__id").eqNullSafe(F.col("__d")) & (F.col("mark") == F.col("__m")), "left").select(*names, "text", "spans")
    schema = "".join(f"k_{i} {docs.schema[c].dataType.simpleString()}, " for i, c in enumerate(keep))
    extra = (", rest string" if digest else "") + (", noted bigint" if note_words is not None else "")
    out = joined.mapInArrow(_remove(names, digest, note_words is not None), f"{schema}n_bytes bigint, n_removed bigint, n_spans bigint, kept string{extra}")
    more = ([F.col("rest").alias(text_col)] if digest else []) + ([F.col("noted").alias("n_passage_bytes")] if note_words is not None else [])
    return out.select(*(F.col(n).alias(c) for n, c in zip(names, keep, strict=True)), "n_bytes", "n_removed", "n_spans", "kept", *more)


def op4_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    # Passages of over 50 words are mostly shorter than LENGTH: what is removed does not show them.
    return remove_repeats(docs, digest=True, note_words=51).withColumnRenamed("kept", "kept_sha256")

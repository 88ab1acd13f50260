"""Near copies of a stated similarity: SimHash fingerprints and pivot tables discard, shingle sets verify.

Two texts link if their sets of word shingles have a Jaccard similarity of ``similarity`` or
more. At 0.8 the fingerprints of linked texts differ in about 10 of 64 bits, more than untouched
blocks of a fingerprint can find, so candidates share a bucket instead: the hash of
``ROWS`` least values of the shingles, of ``BANDS`` such buckets. A pair of similarity s shares
none with probability ``(1 - s**ROWS) ** BANDS`` (1e-7 at 0.8, less above).

Within a bucket pairs are discarded by their pivot distance tables, then by the bits
(more than ``FAR`` of 64 differ: 5 standard deviations from the mean of pairs at 0.8); survivors are
verified with their whole shingle sets.

*Large groups.* Equal sets are one class. First only each bucket's hub, the fingerprint
nearest to the bucket's majority, is compared with the bucket's others. Then only pairs in different
components are, so a group of copies never becomes all its pairs. Texts that share a passage but are
not similar would still be: sketches of the shingle sets discard them where the bucket
is. A sketch has the ``SKETCH`` least 32-bit hashes of a set, mostly all of them; where it is
a part, what is ``DOUBT`` standard deviations below the threshold goes. A bucket of over
``GROUP`` classes is dealt in chunks, and every two chunks meet in a task of their own. In
verification a hub's partners are dealt in parts of ``PARTNERS``, one text in memory at a time.

Edge cases: null and empty texts have no shingles and are copies of each other; fewer words
than a shingle: the whole sequence is one; repeated rows stay and share a component; a null id takes part, and is
nobody's component id unless all ids are null. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import bounded_batches, keyed, pieces, raw, texts
from .components import components
from .scratch import discard, release, written
from .simhash import PIVOTS, SEED, majority, shingle_hashes

ROWS, BANDS, FAR = 5, 40, 24
GROUP, PARTNERS = 5_000, 500
#: Margin: what 32-bit hashes that coincide may change in a whole set's similarity.
SKETCH, DOUBT, MARGIN = 512, 5.5, 0.02


def _multipliers() -> tuple[np.ndarray, np.ndarray]:
    word = lambda i: xxhash.xxh64_intdigest(f"least {i}".encode(), seed=SEED)
    n = ROWS * BANDS
    return np.array([word(i) | 1 for i in range(n)], np.uint64), np.array([word(n + i) for i in range(n)], np.uint64)


_TIMES, _PLUS = _multipliers()


def shingle_set(text: bytes, words: int) -> np.ndarray:
    return np.unique(np.array(shingle_hashes(text, words), np.uint64))


def bucket_keys(found: np.ndarray) -> np.ndarray:
    """A key for each band; equal sets, equal keys. No shingles: no keys."""
    if not len(found):
        return np.zeros(0, np.int64)
    least = np.full(ROWS * BANDS, np.iinfo(np.uint64).max, np.uint64)
    for a in range(0, len(found), 256):
        mixed = found[a : a + 256, None] * _TIMES + _PLUS
        mixed ^= mixed >> np.uint64(32)
        mixed *= np.uint64(0x9E3779B97F4A7C15)
        np.minimum(least, mixed.min(axis=0), out=least)
    bands = least.reshape(BANDS, ROWS)
    return np.array([xxhash.xxh3_64_intdigest(b.tobytes(), seed=i) for i, b in enumerate(bands)], np.uint64).view(np.int64)


def _sets(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                found = [shingle_set(t, words) for t in texts(part.column("text"))]
                keys = [bucket_keys(s) for s in found]
                flat = pa.array(np.concatenate([*keys, np.zeros(0, np.int64)]), pa.int64())
                edges = pa.array(np.r_[0, np.cumsum([len(k) for k in keys])].astype(np.int32), pa.int32())
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), part.column("mark"), pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in found], pa.binary()), pa.array(np.array([majority(s) for s in found], np.uint64).view(np.int64), pa.int64()), pa.ListArray.from_arrays(edges, flat)],
                    ["id", "mark", "sig", "print", "keys"],
                )

    return run


def _near(table: np.ndarray, u: np.ndarray, i: int, among: np.ndarray) -> np.ndarray:
    """Those of ``among`` that i may link to: pivot tables first, then the bits."""
    left = among[np.abs(table[among] - table[i]).max(axis=1) <= FAR]
    return left[np.bitwise_count(u[left] ^ u[i]) <= FAR]


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[dict[str, np.ndarray]]:
    """The members of each bucket in turn, as columns."""
    for batch in batches:
        held = batch.column("held")
        flat, at = held.flatten(), held.offsets.to_numpy()
        at = at - at[0]
        columns = {f.name: flat.field(f.name).to_numpy(zero_copy_only=False) for f in flat.type}
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            yield {k: v[a:b] for k, v in columns.items()}


def _pairs(found: Iterator[tuple[np.ndarray, np.ndarray]], size: int = 50_000) -> Iterator[pa.RecordBatch]:
    held, n = [], 0
    batch = lambda: pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in zip(*held, strict=True)], ["a", "b"])
    for pair in found:
        held.append(pair)
        n += len(pair[0])
        if n >= size:
            yield batch()
            held, n = [], 0
    if held:
        yield batch()


def _hub_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def find() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for g in _groups(batches):
            u = g["print"].view(np.uint64)
            ones = np.unpackbits(u.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
            middle = np.packbits(2 * ones > len(u)).view(">u8").astype(np.uint64)[0]
            hub = int(np.lexsort((g["node"], np.bitwise_count(u ^ middle)))[0])
            table = np.bitwise_count(u[:, None] ^ PIVOTS[None, :]).astype(np.int8)
            near = _near(table, u, hub, np.delete(np.arange(len(u)), hub))
            if len(near):
                yield np.full(len(near), g["node"][hub]), g["node"][near]

    return _pairs(find())


def _sketches(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                found = [np.unique((shingle_set(t, words) >> np.uint64(32)).astype(np.uint32))[:SKETCH].tobytes() for t in texts(part.column("text"))]
                yield pa.RecordBatch.from_arrays([part.column("mark"), pa.array(found, pa.binary())], ["mark", "sketch"])

    return run


class Sketches:
    """The sketches of a bucket's members, for the similarity of one of them to all."""

    def __init__(self, column: pa.Array) -> None:
        data, at = raw(column)
        values = np.frombuffer(data.tobytes(), np.uint32)
        self.at = at // 4
        self.size = np.diff(self.at)
        self.owner = np.repeat(np.arange(len(self.size)), self.size)
        self.values = values
        names, self.token = np.unique(values, return_inverse=True)
        self.mine = np.zeros(len(names), bool)
        # All of a set below its reach is known: everything, where the sketch is whole.
        self.whole = self.size < SKETCH
        self.reach = np.full(len(self.size), np.iinfo(np.uint32).max, np.uint32)
        part = np.flatnonzero(~self.whole)
        self.reach[part] = values[self.at[part + 1] - 1]

    def may_link(self, i: int, similarity: float) -> np.ndarray:
        n = len(self.size)
        own = slice(self.at[i], self.at[i + 1])
        self.mine[self.token[own]] = True
        both = np.bincount(self.owner[self.mine[self.token]], minlength=n)
        self.mine[self.token[own]] = False
        theirs = self.size if self.whole[i] else np.bincount(self.owner[self.values <= self.reach[i]], minlength=n)
        ours = np.searchsorted(self.values[own], self.reach, side="right")
        union = np.maximum(ours + theirs - both, 1)
        doubt = np.where(self.whole & self.whole[i], 0.0, DOUBT * np.sqrt(similarity * (1 - similarity) / union))
        return both >= (similarity - MARGIN - doubt) * union


def _cross_pairs(similarity: float):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for group in keyed(batches, "task"):
            if group.num_rows < 2:
                continue
            u, root, node = group.column("print").to_numpy().view(np.uint64), group.column("root").to_numpy(), group.column("node").to_numpy()
            names, counts = np.unique(root, return_counts=True)
            if len(names) < 2:
                continue
            table = np.bitwise_count(u[:, None] ^ PIVOTS[None, :]).astype(np.int8)
            sketches = Sketches(group.column("sketch").combine_chunks())
            # Rows of the commonest component are only partners: pairs with them are found from the other side.
            main = names[np.argmax(counts)]
            rank = np.where(root == main, len(u), np.arange(len(u)))
            for i in np.flatnonzero(root != main).tolist():
                near = _near(table, u, i, np.flatnonzero((rank > i) & (root != root[i])))
                if len(near):
                    near = near[sketches.may_link(i, similarity)[near]]
                    yield np.minimum(node[near], node[i]), np.maximum(node[near], node[i])

    return lambda batches: _pairs(find(batches))


def _similar(words: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hub: np.ndarray | None = None
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                a_out, b_out = [], []
                for a, node, side, text in zip(*(part.column(k).to_pylist() for k in ("a", "node", "side")), texts(part.column("text")), strict=True):
                    mine = shingle_set(text, words)
                    if side == 0:
                        hub = mine
                        continue
                    both = len(np.intersect1d(hub, mine, assume_unique=True))
                    if both >= similarity * (len(hub) + len(mine) - both) - 1e-9:
                        a_out.append(a)
                        b_out.append(node)
                yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(b_out, pa.int64())], ["a", "b"])

    return run


def _bodies(marked: DataFrame, marks: DataFrame) -> DataFrame:
    """``mark, text`` of the marks. Copies of a text have one mark: partial aggregates leave one of them in each task."""
    return marked.join(marks.distinct(), "mark", "left_semi").groupBy("mark").agg(F.any_value("text").alias("text"))


def _verified(pairs: DataFrame, marked: DataFrame, words: int, similarity: float) -> DataFrame:
    """The pairs ``a, b`` of text marks that are similar. Rows hold one text each; a's comes before its partners'."""
    spark = pairs.sparkSession
    pairs = written(pairs.distinct(), "candidates")
    parts = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / PARTNERS).cast("int").alias("parts"))
    hubs = parts.select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.col("a").alias("node"), F.lit(0).alias("side"))
    others = pairs.join(parts, "a").select("a", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int").alias("part"), F.col("b").alias("node"), F.lit(1).alias("side"))
    asked = hubs.unionByName(others)
    bodies = _bodies(marked, pairs.select(F.col("a").alias("mark")).unionByName(pairs.select(F.col("b").alias("mark"))))
    rows = asked.join(bodies, F.col("node") == F.col("mark")).select("a", "part", "side", "node", "text")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    links = written(rows.repartition(n, "a", "part").sortWithinPartitions("a", "part", "side").mapInArrow(_similar(words, similarity), "a bigint, b bigint"), "similar")
    discard(pairs)
    return links


def similar_documents(docs: DataFrame, *, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text", group: int = GROUP, marks: bool = False, links: DataFrame | None = None) -> DataFrame:
    """``id, component``: component is the smallest id of all documents that links of ``similarity`` or more reach.

    With ``marks`` also ``mark``, the hash of the row's text: rows that repeat an id may lie in different groups.
    links: ``a, b``, marks of texts that are known to belong together; pairs within what they join are not compared again.
    """
    bounded_batches(docs.sparkSession)
    id_type = docs.schema[id_col].dataType.simpleString()
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    marked = docs.select(F.col(id_col).alias("id"), body.alias("text")).withColumn("mark", F.xxhash64("text"))
    sets = written(marked.mapInArrow(_sets(words), f"id {id_type}, mark bigint, sig binary, print bigint, keys array<bigint>"), "sets")
    classes = written(sets.groupBy("sig").agg(F.min("id").alias("first"), F.min("mark").alias("node"), F.any_value("print").alias("print"), F.any_value("keys").alias("keys")), "classes")
    keys = classes.select("node", "print", F.explode("keys").alias("key"))
    sizes = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    blocks = written(keys.join(sizes, "key").select("key", "node", "print", F.ceil(F.col("n") / group).cast("int").alias("chunks")).withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")), "buckets")
    texts_of = marked.select("mark", "text")

    hubs = blocks.groupBy("key", "chunk").agg(F.collect_list(F.struct("node", "print")).alias("held")).where("size(held) > 1").select("held")
    first = _verified(hubs.mapInArrow(_hub_pairs, "a bigint, b bigint"), texts_of, words, similarity)
    if links is not None:
        # Known links are between texts, those found here between the texts that stand for equal sets.
        equal = sets.select("mark", "sig").distinct().join(classes.select("sig", "node"), "sig").where("mark <> node").select(F.col("mark").alias("a"), F.col("node").alias("b"))
        first = first.unionByName(links.select("a", "b")).unionByName(equal)
    now = components(first)
    rooted = blocks.join(now, "node", "left").withColumn("root", F.coalesce("root", "node"))
    open_keys = rooted.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 <> r1").select("key")
    met = written(rooted.join(open_keys, "key", "left_semi"), "open")
    sketches = written(_bodies(texts_of, met.select(F.col("node").alias("mark"))).mapInArrow(_sketches(words), "mark bigint, sketch binary"), "sketches")
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    tasks = (
        met.join(sketches, F.col("node") == F.col("mark")).withColumn("with", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
        .select(F.xxhash64("key", F.least("chunk", "with"), F.greatest("chunk", "with")).alias("task"), "node", "print", "root", "sketch")
        .repartition(n, "task").sortWithinPartitions("task", "node")
    )
    rest = _verified(tasks.mapInArrow(_cross_pairs(similarity), "a bigint, b bigint"), texts_of, words, similarity)
    discard(blocks, met, sketches)
    roots = components(first.unionByName(rest)).withColumnRenamed("root", "to")

    named = classes.select("sig", "first", "node").join(roots, "node", "left").select("sig", "first", F.coalesce("to", "node").alias("root"))
    least = named.groupBy("root").agg(F.min("first").alias("component"))
    release(docs.sparkSession)
    own = ["id", "mark"] if marks else ["id"]
    return sets.select(*own, "sig").join(named.join(least, "root").select("sig", "component"), "sig").select(*own, "component")

"""Near duplicates by DartMinHash signatures, banded joining, exact checks and connected components.

A text is the multiset of its five-word shingles. The j-th occurrence of a shingle is one unit-weight region; hashed
darts fall on a region as a Poisson process over ranks, the same for every text that has the region. A text of total
weight w looks at ranks up to t / w, t = k ln k + 2k, so it throws about t darts whatever its length; every dart
belongs to one of k coordinates, and the earliest dart of a coordinate is its signature there. Two texts agree in a
coordinate with probability equal to their weighted Jaccard similarity.

Signatures are cut into bands; equal bands meet in a bucket. Pairs are never enumerated within a bucket: each round
compares a bucket's members with one pivot (the member whose other buckets are largest, so the middle of a group and
the same one in all its buckets), links those with similarity of at least `threshold`, and drops a bucket once its
members share a class. Jaccard distance is a metric, so a linked member can be left out of later rounds unless some
unlinked one is within 2 (1 - threshold) of the pivot. The texts of the buckets left after `rounds` rounds meet by an
exact similarity join between different classes (`links_between`): regions that only one class has can be in no overlap,
and a text enters only by the few rarest of its other regions that an overlap large enough must touch. So no candidate
link between different texts is lost, and texts that nothing can reach cost no comparison. Components are found by
contraction on tables, never on the driver.

Copies (equal words but for case) are one node from the start, so groups of copies cost one row per copy.

Defined cases: a null text is alone in its class (rows repeated under one id share it); texts without words are
copies of each other; a text of fewer than five words is one shingle; very long texts are read whole, a bounded number
of words at a time; texts with equally good pivots go by the smallest id; an empty table gives an empty result; further
columns are ignored, whatever their names; an id repeated with different texts counts as one row of each text, and its
candidates are checked with one of them (the pipeline gives such rows keys of their own first).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.llm import common

SHINGLE = 5
BANDS, ROWS = 20, 5
THRESHOLD = 0.8
ROUNDS = 2
#: A region that more texts than this enter by is joined in that many blocks.
BLOCK = 1000
BATCH_WORDS = 40_000

_M = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all lower-cased words end to end, and the bounds of each text among them."""
    split = pc.ascii_split_whitespace(pc.utf8_lower(pa.array([t or "" for t in texts], pa.large_string())))
    flat, starts = split.flatten(), split.offsets.to_numpy().astype(np.int64)
    real = pc.not_equal(flat, "").to_numpy(zero_copy_only=False)
    coded = flat.dictionary_encode()
    distinct = np.fromiter((xxhash.xxh64_intdigest(w) for w in coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    hashes = distinct[coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)] if len(flat) else np.zeros(0, np.uint64)
    bounds = np.concatenate([[0], np.cumsum(real)])[starts]
    return hashes[real], bounds


def regions(hashes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of the unit regions (shingle, occurrence) of every text, sorted within a text, and the bounds of each text."""
    n = np.diff(bounds)
    count = np.where(n >= SHINGLE, n - SHINGLE + 1, np.minimum(n, 1))
    ends = np.cumsum(count)
    doc = np.repeat(np.arange(len(n)), count)
    place = np.arange(int(count.sum())) - np.repeat(ends - count, count) + np.repeat(bounds[:-1], count)
    stop = np.repeat(bounds[1:], count)
    shingle = np.zeros(len(doc), np.uint64)
    for j in range(SHINGLE):
        inside = place + j < stop
        shingle[inside] += mix(hashes[place[inside] + j] + _M[j]) * _M[j]
    shingle = mix(shingle)
    order = np.lexsort((shingle, doc))
    shingle = shingle[order]
    new = np.ones(len(doc), bool)
    new[1:] = (shingle[1:] != shingle[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    occurrence = np.arange(len(doc)) - np.repeat(first, np.diff(np.append(first, len(doc))))
    again = occurrence > 0
    if again.any():
        shingle[again] = mix(shingle[again] + occurrence[again].astype(np.uint64) * _M[0])
    return shingle, np.concatenate([[0], ends])


def signatures(region: np.ndarray, bounds: np.ndarray, k: int) -> np.ndarray:
    """(texts x k) ids of the earliest dart per coordinate; rows of texts without regions are 0."""
    weight = np.diff(bounds)
    out = np.zeros((len(weight), k), np.uint64)
    todo = np.flatnonzero(weight)
    reach = k * np.log(k) + 2.0 * k
    while len(todo):
        owner = np.repeat(np.arange(len(todo)), weight[todo])
        starts = np.cumsum(weight[todo]) - weight[todo]
        unit = region[np.arange(len(owner)) - np.repeat(starts, weight[todo]) + np.repeat(bounds[todo], weight[todo])]
        limit = (reach / weight[todo])[owner]
        rank, darts = np.zeros(len(unit)), []
        step = 0
        while len(unit):
            step += 1
            dart = mix(unit + np.uint64(step * int(_M[1]) % 2**64))
            # Gaps between the ranks of a region's darts are exponential: a Poisson process of rate one.
            rank = rank - np.log((((dart >> np.uint64(11)).astype(np.float64)) + 0.5) * 2.0**-53)
            live = rank <= limit
            unit, rank, limit, owner, dart = unit[live], rank[live], limit[live], owner[live], dart[live]
            darts.append((owner, rank, dart))
        own, rank, dart = (np.concatenate(x) for x in zip(*darts, strict=True))
        # The coordinate comes from a second hash, so it is independent of the rank.
        identity = mix(dart ^ _M[2])
        slot = own * k + (identity % np.uint64(k)).astype(np.int64)
        order = np.argsort(-rank, kind="stable")
        filled = np.zeros(len(todo) * k, np.uint64)
        filled[slot[order]] = identity[order] | np.uint64(1)
        filled = filled.reshape(len(todo), k)
        full = (filled != 0).all(axis=1)
        out[todo[full]] = filled[full]
        # Rarely a coordinate got no dart; those texts look further, where the darts seen stay the earliest.
        todo = todo[~full]
        reach *= 2
    return out


def band_keys(signature: np.ndarray, bands: int, rows: int) -> np.ndarray:
    cut = signature.reshape(len(signature), bands, rows)
    key = np.broadcast_to(mix(np.arange(1, bands + 1).astype(np.uint64) * _M[3]), cut.shape[:2]).copy()
    for j in range(rows):
        key = mix(key ^ cut[:, :, j]) + _M[4]
    return key.view(np.int64)


def by_words(sizes) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about BATCH_WORDS words, given the rows' sizes in characters."""
    start, size = 0, 0
    for i, n in enumerate(sizes):
        size += int(n) // 6 + 1
        if size >= BATCH_WORDS:
            yield start, i + 1
            start, size = i + 1, 0
    if start < len(sizes):
        yield start, len(sizes)


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, copy_key (equal for copies), bands (one key per band; empty without words)."""

    schema = pa.schema([("doc_id", pa.int64()), ("copy_key", pa.binary()), ("bands", pa.list_(pa.int64()))])

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False)
            # Slices of a bounded number of words become Python objects, not whole batches.
            for a, b in by_words(sizes):
                ids, texts = batch.column(0).slice(a, b - a).to_pylist(), batch.column(1).slice(a, b - a).to_pylist()
                hashes, bounds = word_hashes(texts)
                keys = [hashlib.md5(hashes[bounds[i]:bounds[i + 1]].tobytes() if t is not None else f"null {d}".encode()).digest() for i, (t, d) in enumerate(zip(texts, ids, strict=True))]
                region, limits = regions(hashes, bounds)
                band = band_keys(signatures(region, limits, bands * rows), bands, rows)
                some = np.diff(limits) > 0
                yield pa.RecordBatch.from_pydict({"doc_id": ids, "copy_key": keys, "bands": [x if s else x[:0] for x, s in zip(band, some, strict=True)]}, schema=schema)
            # What Arrow keeps for reuse would stay with the worker through all later stages.
            pa.default_memory_pool().release_unused()

    return docs.select("doc_id", "text").mapInArrow(sketched, "doc_id long, copy_key binary, bands array<long>")


def similarities(pairs: DataFrame, units: DataFrame) -> DataFrame:
    """a, b, similarity (weighted Jaccard of shingle multisets) of each pair of ids, from the regions of their texts."""
    left = units.select(F.col("doc_id").alias("a"), F.col("units").alias("a_units"))
    right = units.select(F.col("doc_id").alias("b"), F.col("units").alias("b_units"))
    both = F.size(F.array_intersect("a_units", "b_units"))
    counted = pairs.join(left, "a").join(right, "b").select("a", "b", both.alias("both"), (F.size("a_units") + F.size("b_units")).alias("all"))
    return counted.select("a", "b", F.when(F.col("all") > 0, F.col("both") / (F.col("all") - F.col("both"))).otherwise(1.0).alias("similarity"))


def components(edges: DataFrame) -> DataFrame:
    """node, label (smallest id of the component) of every node of the edges (a, b).

    Each round maps a node to its smallest neighbour, follows that map twice more by self-joins, and replaces the
    graph by its image; a component's image is connected exactly if it was, and its smallest node stays.
    """
    now = edges.filter("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct()
    now = common.materialise(now)
    labels = now.select(F.col("hi").alias("node")).union(now.select("lo")).distinct().withColumn("label", F.col("node"))
    while not now.isEmpty():
        up = now.groupBy("hi").agg(F.min("lo").alias("to"))
        up = common.materialise(up)
        for _ in range(2):
            again = up.select(F.col("hi").alias("to"), F.col("to").alias("next"))
            up = up.join(again, "to", "left").select("hi", F.coalesce("next", "to").alias("to"))
        up = common.materialise(up)
        a = up.select(F.col("hi").alias("hi"), F.col("to").alias("a"))
        b = up.select(F.col("hi").alias("lo"), F.col("to").alias("b"))
        image = now.join(a, "hi", "left").join(b, "lo", "left").select(F.coalesce("a", "hi").alias("a"), F.coalesce("b", "lo").alias("b")).filter("a <> b")
        now = common.materialise(image.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct())
        labels = labels.join(up.select(F.col("hi").alias("label"), "to"), "label", "left").select("node", F.coalesce("to", "label").alias("label"))
    return common.materialise(labels)


def unit_regions(texts: DataFrame) -> DataFrame:
    """doc_id, units (ids of its regions) of texts."""
    schema = pa.schema([("doc_id", pa.int64()), ("units", pa.list_(pa.int64()))])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False)
            for a, b in by_words(sizes):
                region, limits = regions(*word_hashes(batch.column(1).slice(a, b - a).to_pylist()))
                units = pa.ListArray.from_arrays(pa.array(limits, pa.int32()), pa.array(region.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), units], schema=schema)

    return texts.select("doc_id", "text").mapInArrow(cut, "doc_id long, units array<long>")


def links_between(units: DataFrame, label: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """a, b: every pair of texts (doc_id, units) of different labels (doc_id, label) that may reach the threshold.

    An overlap of texts with different labels holds only regions that several labels have. In one order of all regions
    (the others first, then from rare to frequent), two texts whose overlap is at least `need` share a region among
    the first n - need + 1 of each, and behind the first one that they share enough must be left in both.
    """
    share = threshold / (1 + threshold)
    units = units.join(label, "doc_id").select("doc_id", "label", F.size("units").alias("n"), F.explode("units").alias("unit"))
    units = common.materialise(units)
    shared = units.groupBy("unit").agg(F.count(F.lit(1)).alias("df"), F.min("label").alias("low"), F.max("label").alias("high")).filter("low <> high").select("unit", "df")
    own = W.partitionBy("doc_id")
    left = F.col("n") - (F.col("n") - F.count(F.lit(1)).over(own) + F.row_number().over(own.orderBy("df", "unit")) - 1)
    entry = units.join(shared, "unit").withColumn("left", left).filter(F.col("left") >= threshold * F.col("n") - 1e-6).select("doc_id", "label", "n", "unit", "left")
    entry = common.materialise(entry)
    met = entry.groupBy("unit").agg(F.min("n").alias("least"), F.min("label").alias("low"), F.max("label").alias("high"))
    entry = entry.join(met.filter("low <> high").select("unit", "least"), "unit").filter(F.col("left") >= share * (F.col("n") + F.col("least")) - 1e-6)
    entry = common.materialise(entry)
    blocks = entry.groupBy("unit").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"), F.min("label").alias("low"), F.max("label").alias("high"))
    entry = common.materialise(entry.join(blocks.filter("low <> high").select("unit", "blocks"), "unit"))

    def side(name: str) -> list:
        return [F.col(c).alias(f"{name}_{c}") for c in ("doc_id", "label", "n", "left")]

    one = entry.select("unit", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int").alias("block"), *side("a"))
    other = entry.select("unit", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), *side("b"))
    enough = F.least("a_left", "b_left") >= share * (F.col("a_n") + F.col("b_n")) - 1e-6
    pairs = one.join(other, (one["unit"] == other["unit"]) & (one["block"] == other["block"]) & (F.col("a_label") < F.col("b_label")) & enough)
    return pairs.select(F.col("a_doc_id").alias("a"), F.col("b_doc_id").alias("b")).distinct()


def classes(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, copy_of (smallest id of its copies), class_id (smallest id of its class): one row per input row."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    drawn = common.materialise(sketch(docs, bands, rows))
    copies = common.materialise(drawn.groupBy("copy_key").agg(F.min("doc_id").alias("copy_of")))
    # One row per distinct text: joined on ids, which no group of copies makes uneven.
    unique = drawn.join(copies.select(F.col("copy_of").alias("doc_id")), "doc_id", "left_semi").select("doc_id", "bands").dropDuplicates(["doc_id"])
    member = common.materialise(unique.select("doc_id", F.explode("bands").alias("bucket")))
    several = member.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    shared = common.materialise(member.join(several, "bucket"))
    # The more texts share one's buckets, the nearer it is to the middle of its group.
    rank = common.materialise(shared.groupBy("doc_id").agg((-F.sum("n")).alias("rank")))
    alive = common.materialise(shared.select("bucket", "doc_id").join(rank, "doc_id"))
    # The regions of every text with company, made once: pairs are compared inside the JVM, whose memory is bounded.
    units = common.materialise(unit_regions(docs.join(rank, "doc_id", "left_semi")).dropDuplicates(["doc_id"]))

    none = docs.sparkSession.createDataFrame([], "a long, b long, similarity double")
    edges, label = none, none.select(F.col("a").alias("node"), F.col("b").alias("label"))
    for _ in range(rounds):
        pivots = alive.groupBy("bucket").agg(F.min(F.struct("rank", "doc_id"))["doc_id"].alias("pivot"))
        alive = common.materialise(alive.join(common.materialise(pivots), "bucket"))
        pairs = alive.filter("doc_id <> pivot").select(F.col("doc_id").alias("a"), F.col("pivot").alias("b")).distinct()
        found = common.materialise(similarities(pairs, units))
        edges = edges.union(found.filter(F.col("similarity") >= threshold))
        label = components(edges)
        seen = alive.join(found.withColumnsRenamed({"a": "doc_id", "b": "pivot"}), ["doc_id", "pivot"], "left")
        seen = seen.join(label.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("label", F.coalesce("label", "doc_id"))
        seen = common.materialise(seen)
        state = seen.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.max(F.when(F.col("similarity") < threshold, F.col("similarity"))).alias("close"))
        # Unlinked members go on; linked ones only if a link to an unlinked one isn't excluded by the triangle inequality.
        state = common.materialise(state.filter("low <> high").select("bucket", "close"))
        kept = seen.filter("doc_id <> pivot").join(state, "bucket").filter(
            (F.col("similarity") < threshold) | ((F.col("similarity") < 1) & (F.col("close") >= 1 - 2 * (1 - threshold)) & (1 - F.col("similarity") + 1e-9 >= 1 - F.col("close") - (1 - threshold))))
        kept = common.materialise(kept.select("bucket", "doc_id", "label", "rank"))
        mixed = kept.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high")).filter("low <> high").select("bucket")
        alive = common.materialise(kept.join(common.materialise(mixed), "bucket").select("bucket", "doc_id", "rank"))
        if alive.isEmpty():
            break
    else:
        rest = alive.select("doc_id").distinct().join(label.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("label", F.coalesce("label", "doc_id"))
        left = common.materialise(links_between(units, common.materialise(rest), threshold))
        found = common.materialise(similarities(left, units).filter(F.col("similarity") >= threshold))
        if not found.isEmpty():
            label = components(edges.union(found))
    named = copies.join(label.withColumnRenamed("node", "copy_of"), "copy_of", "left").select("copy_key", "copy_of", F.coalesce("label", "copy_of").alias("class_id"))
    return drawn.select("doc_id", "copy_key").join(common.materialise(named), "copy_key").select("doc_id", "copy_of", "class_id")


def op5_dart_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(common.documents(spark, sf_dir)).withColumn("kept", F.col("doc_id") == F.col("class_id"))

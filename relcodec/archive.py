"""Archives: a model file and a Parquet table of coded blocks.

compress = learn a structure on a bounded sample, fit masses in one scan, code in one map-only pass. A block row is
(block_id, nrows, nbits, payload, offsets, zone): `offsets` holds the bit place of every INDEX_EVERY-th code (of each, if
they are long), the codes between are found by decoding, since each ends by itself. The model is written last, so an archive without it is
incomplete. Blocks are numbered by partition and order within it, so a repeated task writes the same rows.
"""

from __future__ import annotations

import dataclasses
import functools
import itertools
import json
import pickle
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec import codecs
from relcodec.network import Network, Node, Structure, code_sizes, domain_of, fit_networks, fit_parameters, image_values, learn_structure, near_functions, symbols_of, with_key_parents
from relcodec.schema import TableSpec, infer_spec, quoted
from relcodec.sources.stored import Stored

BLOCK_ROWS = 8192
INDEX_EVERY = 16
#: Mean bits of a code from which on every code is indexed.
LONG_CODE = 2048
#: Codes that a task remembers while it decodes delta-coded blocks.
KNOWN_CODES = 4096
#: Bytes of images that a block should not exceed.
BLOCK_BYTES = 4_000_000
SAMPLE_ROWS = 2000
BLOCKS = "block_id long, nrows int, nbits long, payload binary, offsets binary, zone map<string,struct<lo:long,hi:long>>, delta boolean"


@dataclass(frozen=True)
class Options:
    structure: Structure | str = "learn"  # or "empty", or a structure given by hand
    sample_rows: int = SAMPLE_ROWS
    sample: str = "random"
    seed: int = 0
    score: str = "mdl_scaled"
    max_parents: int = 3
    delta: bool = False
    block_rows: int = BLOCK_ROWS
    string_order: int = 1
    tolerance_pct: float | None = None
    zones: tuple[str, ...] = ()
    keys: bool = True  # look for keys whose values are too many for the sample, and try them on all rows


@dataclass
class Archive:
    """Where an archive lies, and what reads it."""

    path: str
    network: Network
    expansion: codecs.Expansion

    def blocks(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema(BLOCKS).parquet(f"{self.path}/blocks")


def sample_first(images: DataFrame, key: str, n: int = SAMPLE_ROWS) -> DataFrame:
    return images.orderBy(key).limit(n)


def sample_random(images: DataFrame, n: int = SAMPLE_ROWS, seed: int = 0) -> DataFrame:
    """n rows drawn evenly: the smallest of seeded random numbers, one a row, so equal rows are drawn as often as they occur.

    Each task keeps its own n smallest, so no more than that leaves it."""
    return images.withColumn("_h", F.rand(seed)).orderBy("_h").limit(n).drop("_h")


def symbols_of_sample(rows: list, spec: TableSpec) -> tuple[dict[str, np.ndarray], dict[str, int]]:
    """Parent-side symbols of sample rows; the same resolution serves child and parent in the search."""
    out, domains = {}, {}
    for a in spec.attributes:
        values = image_values(pa.array([r[a.name] for r in rows], pa.float64() if a.bitwise else pa.int64() if a.numeric else pa.string()), a)
        out[a.name] = np.maximum(symbols_of(values, a, True), 0)
        domains[a.name] = domain_of(a, True)
    return out, domains


def learn(images: DataFrame, spec: TableSpec, options: Options) -> Structure:
    if isinstance(options.structure, Structure):
        return options.structure
    if options.structure == "empty" or len(spec.attributes) < 2:
        return Structure.empty(spec.names)
    if options.sample == "first":
        rows = images.limit(options.sample_rows).collect()
    else:
        rows = sample_random(images, options.sample_rows, options.seed).collect()
    if not rows:
        return Structure.empty(spec.names)
    symbols, domains = symbols_of_sample(rows, spec)
    scale = max(1.0, images.count() / len(rows)) if options.score == "mdl_scaled" else 1.0
    structure = learn_structure(symbols, domains, options.max_parents, options.score, scale)
    return with_key_parents(images, spec, structure, symbols, domains) if options.keys else structure


def samples_random(images: DataFrame, sizes: dict[int, int], rows: int) -> dict[int, list]:
    """What `sample_random` gives for each seed (with its size), from one scan: rows whose random number is far below that
    of the last one drawn, as a rule, are all that leaves the tasks."""
    names = {seed: f"_h{seed}" for seed in sizes}
    below = [F.col(names[seed]) < (n + 10 * n**0.5 + 100) / max(rows, 1) for seed, n in sizes.items()]
    numbers, keep = {h: F.rand(seed) for seed, h in names.items()}, functools.reduce(lambda a, b: a | b, below)
    found = (images.drawn(numbers, keep) if isinstance(images, Stored) else images.withColumns(numbers).filter(keep)).collect()
    out = {}
    for seed, n in sizes.items():
        own = sorted((r for r in found if r[names[seed]] < (n + 10 * n**0.5 + 100) / max(rows, 1)), key=lambda r: r[names[seed]])[:n]
        out[seed] = own if len(own) == min(n, rows) else sample_random(images, n, seed).collect()
    return out


def in_tasks(spark: SparkSession, n: int, work: Callable[[int], Any]) -> list:
    """work(0) to work(n - 1), a task each; they give plain values."""
    def done(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_pydict({"id": [i], "result": [pickle.dumps(work(i))]})

    found = {r["id"]: pickle.loads(r["result"]) for r in spark.range(0, n, 1, n).mapInArrow(done, "id long, result binary").collect()}
    return [found[i] for i in range(n)]


def fit_all(images: DataFrame, spec: TableSpec, options: list[Options], rows: int) -> list[Network]:
    """Networks under several options, as `learn` and `fit_parameters` give each: one scan draws all samples, tasks side by
    side search for the structures, and one scan counts for all (a second one, if large families need it)."""
    searched = [i for i, o in enumerate(options) if not isinstance(o.structure, Structure) and o.structure != "empty" and o.sample != "first" and len(spec.attributes) > 1 and rows]
    structures = [None if i in searched else learn(images, spec, o) for i, o in enumerate(options)]
    pairs: list[list[tuple[str, str]]] = [[] for _ in options]
    if searched:
        sizes: dict[int, int] = {}
        for i in searched:
            sizes[options[i].seed] = max(sizes.get(options[i].seed, 0), options[i].sample_rows)
        drawn = samples_random(images, sizes, rows)
        asked = [(options[i], *symbols_of_sample(drawn[options[i].seed][: options[i].sample_rows], spec)) for i in searched]

        def search(k: int) -> tuple[dict[str, tuple[str, ...]], list[tuple[str, str]]]:
            o, symbols, domains = asked[k]
            scale = max(1.0, rows / len(next(iter(symbols.values())))) if o.score == "mdl_scaled" else 1.0
            return learn_structure(symbols, domains, o.max_parents, o.score, scale).parents, near_functions(symbols, domains) if o.keys else []

        for i, (parents, near) in zip(searched, in_tasks(images.sparkSession, len(searched), search), strict=True):
            structures[i], pairs[i] = Structure(parents), [(p, c) for p, c in near if spec[c].kind not in ("string", "user")]
    networks: list[Network | None] = [None] * len(options)
    for order in dict.fromkeys(o.string_order for o in options):
        at = [i for i, o in enumerate(options) if o.string_order == order]
        for i, network in zip(at, fit_networks(images, spec, [structures[i] for i in at], [pairs[i] for i in at], string_order=order), strict=True):
            networks[i] = network
    return networks


def fit(df: DataFrame, options: Options = Options(), spec: TableSpec | None = None) -> tuple[DataFrame, Network, codecs.Expansion]:
    """(images of df, fitted network, how columns were expanded)."""
    expansion = codecs.Expansion.infer(df) if spec is None else codecs.Expansion.none(df)
    wide = expansion.expand(df)
    spec = spec or infer_spec(wide)
    if options.tolerance_pct is not None:
        spec = spec.with_tolerance_pct(options.tolerance_pct)
    images = spec.images(wide)
    return images, fit_parameters(images, spec, learn(images, spec, options), string_order=options.string_order), expansion


def encode(images: DataFrame, network: Network, options: Options = Options()) -> DataFrame:
    """Block rows of images: map-only; texts make smaller batches."""
    shared = images.sparkSession.sparkContext.broadcast(network.to_json())
    zones, block_rows, delta = options.zones, options.block_rows, options.delta
    names = network.spec.names

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = Network.from_json(shared.value)
        partition = TaskContext.get().partitionId()
        for made, table in enumerate(block_tables(batches, block_rows)):
            columns = {n: image_values(table.column(n), net.spec[n]) for n in names}
            row = pack(net, columns, table.num_rows, delta)
            zone = [(z, {"lo": min((v for v in columns[z] if v is not None), default=None), "hi": max((v for v in columns[z] if v is not None), default=None)}) for z in zones]
            yield pa.RecordBatch.from_pydict({"block_id": [(partition << 32) + made], "nrows": [table.num_rows], "nbits": [row[0]], "payload": [row[1]], "offsets": [row[2]], "zone": [zone], "delta": [delta]}, schema=BLOCK_ARROW)

    return images.mapInArrow(coded, BLOCKS)


def block_tables(batches: Iterator[pa.RecordBatch], block_rows: int) -> Iterator[pa.Table]:
    """The rows of each block."""
    held: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        held.append(batch)
        count += batch.num_rows
        size = min(block_rows, max(1, BLOCK_BYTES * batch.num_rows // max(batch.nbytes, 1)))
        while count >= size:
            table = pa.Table.from_batches(held)
            yield table.slice(0, size)
            rest = table.slice(size)
            held, count = rest.to_batches(), rest.num_rows
    if count:
        yield pa.Table.from_batches(held)


def encoded_bytes(images: DataFrame, networks: list[Network], options: list[Options]) -> list[dict[str, int]]:
    """What `archive_bytes` gives for an archive by each network (all over the same attributes), from one scan in which every
    row is coded by all of them; the coded blocks are counted, not kept.

    A block's bytes follow from the bits of its codes, so codes are put together only where they are to be delta-coded."""
    block_rows = options[0].block_rows
    if any(o.block_rows != block_rows for o in options):
        return [encoded_bytes(images, [network], [o])[0] for network, o in zip(networks, options, strict=True)]
    # Nodes that several networks have travel once, and networks that have all their nodes in common are one.
    nodes = list({id(node): node for network in networks for node in network.nodes}.values())
    place = {id(node): i for i, node in enumerate(nodes)}
    asked = [(tuple(place[id(node)] for node in network.nodes), o.delta) for network, o in zip(networks, options, strict=True)]
    distinct = list(dict.fromkeys(asked))
    shared = images.sparkSession.sparkContext.broadcast((networks[0].spec.to_json(), [node.to_record(lambda x: x) for node in nodes]))

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spec = TableSpec.from_json(shared.value[0])
        made = [Node.from_record(r, spec) for r in shared.value[1]]
        nets = [(Network(spec, [made[k] for k in own]), delta) for own, delta in distinct]
        plain = [i for i, (_, delta) in enumerate(nets) if not delta]
        total = np.zeros((len(nets), 4), np.int64)
        for table in block_tables(batches, block_rows):
            columns = {a.name: image_values(table.column(a.name), a) for a in spec.attributes}
            for i, sizes in zip(plain, code_sizes([nets[i][0].nodes for i in plain], columns, table.num_rows), strict=True):
                nbits = int(sizes.sum())
                total[i] += ((nbits + 7) // 8, len(code_index(sizes)), table.num_rows, nbits)
            for i, (net, delta) in enumerate(nets):
                if delta:
                    nbits, payload, offsets = pack(net, columns, table.num_rows, delta)
                    total[i] += (len(payload), len(offsets), table.num_rows, nbits)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), *(pa.array(total[:, k]) for k in range(4))], names=["i", "codes", "index", "rows", "code_bits"])

    def model(i: int) -> int:
        spec = TableSpec.from_json(shared.value[0])
        network = Network(spec, [Node.from_record(shared.value[1][k], spec) for k in distinct[i][0]])
        return len(zlib.compress(json.dumps({"network": network.to_json()}).encode(), 9))

    sums = {r["i"]: r for r in images.mapInArrow(coded, "i long, codes long, index long, rows long, code_bits long").groupBy("i").agg(*[F.sum(c).alias(c) for c in ("codes", "index", "rows", "code_bits")]).collect()}
    models = in_tasks(images.sparkSession, len(distinct), model)
    found = [{"model": models[i], **{c: int(sums[i][c]) if i in sums else 0 for c in ("codes", "index", "rows", "code_bits")}} for i in range(len(distinct))]
    return [found[distinct.index(x)] for x in asked]


BLOCK_ARROW = pa.schema([("block_id", pa.int64()), ("nrows", pa.int32()), ("nbits", pa.int64()), ("payload", pa.binary()), ("offsets", pa.binary()),
                         ("zone", pa.map_(pa.string(), pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))), ("delta", pa.bool_())])


def pack(net: Network, columns: dict[str, np.ndarray], rows: int, delta: bool) -> tuple[int, bytes, bytes]:
    """(bits, payload, offsets) of one block."""
    coder = net.encoder(columns, rows)
    if delta:
        bits = delta_encode(*coder.codes())
        return len(bits), np.packbits(bits).tobytes(), b""
    payload, sizes = coder.packed()
    return int(sizes.sum()), payload, code_index(sizes)


def code_index(sizes: np.ndarray) -> bytes:
    """The offsets of a block by the bits of its codes."""
    # Long codes are indexed one by one: their index is small beside them, and they are decoded side by side.
    every = INDEX_EVERY if int(sizes.sum()) < LONG_CODE * max(len(sizes), 1) else 1
    starts = (np.cumsum(sizes) - sizes)[::every]
    return bytes([every]) + zlib.compress(np.diff(starts, prepend=0).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes(), 9)


def delta_encode(bits: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Codes sorted; the first floor(log2 n) bits of each become the unary gap to the one before (the first's to 0); the
    rest is kept. Codes shorter than the prefix are padded with zeros."""
    n = len(sizes)
    length = max(0, n.bit_length() - 1)
    starts = np.cumsum(sizes) - sizes
    codes = sorted(bits[s: s + k].tobytes() + b"\0" * max(0, length - int(k)) for s, k in zip(starts, sizes, strict=True))
    out, last = [], 0
    weights = 1 << np.arange(length - 1, -1, -1)
    for code, equal in itertools.groupby(codes):
        own = np.frombuffer(code, np.uint8)
        prefix = int((own[:length] * weights).sum()) if length else 0
        again = np.concatenate([np.zeros(1, np.uint8), own[length:]])
        out += [np.ones(prefix - last, np.uint8), np.tile(again, sum(1 for _ in equal))]
        last = prefix
    return np.concatenate(out) if out else np.zeros(0, np.uint8)


def repeats(bits: np.ndarray, at: int, pattern: np.ndarray, most: int) -> int:
    """How often the pattern follows itself from `at` on, at most `most` times: looked at in ever more places at once."""
    found, size, ahead = 0, len(pattern), 1
    while found < most:
        ahead = min(ahead, most - found, (len(bits) - at) // size)
        if ahead < 1:
            break
        equal = (bits[at: at + ahead * size].reshape(ahead, size) == pattern).all(axis=1)
        if not equal.all():
            return found + int(equal.argmin())
        found, at, ahead = found + ahead, at + ahead * size, ahead * 4
    return found


def delta_decode(net: Network, payload: bytes, nbits: int, rows: int, known: dict[int, dict[bytes, dict]] | None = None) -> dict[str, np.ndarray]:
    """Columns of a delta-coded block, in the order of their codes. A code's end is known once it is decoded, so distinct
    codes are rebuilt one after the other. `known`: codes decoded before by their bits, by length, which the blocks of a
    task share."""
    known = {} if known is None else known
    bits = np.unpackbits(np.frombuffer(payload, np.uint8))[:nbits]
    length = max(0, rows.bit_length() - 1)
    at, prefix, done, parts = 0, 0, 0, []
    while done < rows:
        while bits[at]:
            prefix += 1
            at += 1
        at += 1
        head = np.frombuffer(format(prefix, "b").zfill(length).encode(), np.uint8) - 48 if length else np.zeros(0, np.uint8)
        start = np.concatenate([head, bits[at: at + 4096]])
        bare = start.tobytes()
        # No code begins another, so one that was met before is told by its bits.
        size = next((k for k, codes in known.items() if bare[:k] in codes), 0)
        if size:
            columns = known[size][bare[:size]]
        else:
            columns, ends = net.decode(np.packbits(start).tobytes(), np.zeros(1, np.int64))
            if ends[0] > length + 4096:
                columns, ends = net.decode(np.packbits(np.concatenate([head, bits[at:]])).tobytes(), np.zeros(1, np.int64))
            size = int(ends[0])
            if 0 < size <= len(start) and sum(map(len, known.values())) < KNOWN_CODES:
                known.setdefault(size, {})[bare[:size]] = columns
        stop = at + max(0, size - length)
        # Equal codes follow each other: no gap and the same rest again, so they need not be decoded.
        same = 1 + repeats(bits, stop, np.concatenate([np.zeros(1, np.uint8), bits[at: stop]]), rows - done - 1)
        at = stop + (same - 1) * (1 + stop - at)
        done += same
        parts.append({n: np.repeat(v, same) for n, v in columns.items()})
    return {n: np.concatenate([p[n] for p in parts]) for n in parts[0]} if parts else {}


def unpack(net: Network, payload: bytes, offsets: bytes, rows: int, nbits: int, delta: bool, last: int | None = None, wanted: np.ndarray | None = None, known: dict | None = None) -> dict[str, np.ndarray]:
    """Columns of a block: the runs between indexed codes are decoded side by side, one code of each at a time.

    `wanted`: places of the rows to decode (only their runs are touched); `last`: how many nodes are needed.
    """
    if delta:
        columns = delta_decode(net, payload, nbits, rows, known)
        return {k: v[wanted] if wanted is not None else v for k, v in columns.items()}
    every = offsets[0]
    gaps = np.ascontiguousarray(np.frombuffer(zlib.decompress(offsets[1:]), np.uint8).reshape(4, -1).T).view("<u4").ravel()
    starts = np.cumsum(gaps.astype(np.int64))
    runs = np.arange(len(starts)) if wanted is None else np.unique(wanted // every)
    at = starts[runs]
    parts: list[dict[str, np.ndarray]] = []
    places: list[np.ndarray] = []
    for k in range(every):
        live = runs * every + k < rows
        if not live.any():
            break
        # Only whole codes tell where the next one starts; the last of each run may stop early.
        stop = last if k == every - 1 else None
        columns, ends = net.decode(payload, at[live], stop)
        at[live] = ends
        parts.append({n: columns[n] for n in (list(columns)[:last] if last else columns)})
        places.append(runs[live] * every + k)
    order = np.argsort(np.concatenate(places))
    out = {n: np.concatenate([p[n] for p in parts])[order] for n in parts[0]}
    if wanted is not None:
        sorted_places = np.concatenate(places)[order]
        at = np.searchsorted(sorted_places, wanted)
        out = {n: v[at] for n, v in out.items()}
    return out


def to_arrow(columns: dict[str, np.ndarray], spec: TableSpec, names: list[str]) -> pa.RecordBatch:
    def column(n: str) -> pa.Array:
        if not spec[n].numeric:
            return pa.array(columns[n].tolist(), pa.string())
        null = np.array([v is None for v in columns[n]], bool)
        whole = np.where(null, 0, columns[n]).astype(np.int64)
        return pa.array(spec[n].doubles_of(whole) if spec[n].bitwise else whole, mask=null)

    return pa.RecordBatch.from_arrays([column(n) for n in names], names=names)


def decode(blocks: DataFrame, network: Network, names: list[str] | None = None) -> DataFrame:
    """Images of all rows of blocks (of the named attributes: nodes after the last one needed are not decoded)."""
    shared = blocks.sparkSession.sparkContext.broadcast(network.to_json())
    order = network.structure.coding_order
    names = [n for n in network.spec.names if names is None or n in names]
    last = max((order.index(n) for n in names), default=0) + 1

    def decoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net, known = Network.from_json(shared.value), {}
        for batch in batches:
            for row in batch.to_pylist():
                columns = unpack(net, row["payload"], row["offsets"], row["nrows"], row["nbits"], row["delta"], None if last == len(order) else last, known=known)
                if columns:
                    yield to_arrow(columns, net.spec, names)

    return blocks.select("payload", "offsets", "nrows", "nbits", "delta").mapInArrow(decoded, network.spec.image_schema(names))


def compress(df: DataFrame, path: str, options: Options = Options(), spec: TableSpec | None = None) -> Archive:
    images, network, expansion = fit(df, options, spec)
    encode(images, network, options).write.mode("overwrite").option("compression", "none").parquet(f"{path}/blocks")
    model = json.dumps({"network": network.to_json(), "expansion": expansion.to_json()})
    df.sparkSession.createDataFrame([(model,)], "value string").coalesce(1).write.mode("overwrite").option("compression", "gzip").text(f"{path}/model")
    return Archive(path, network, expansion)


def open_archive(spark: SparkSession, path: str) -> Archive:
    raw = json.loads(spark.read.option("wholetext", "true").text(f"{path}/model").first()[0])
    return Archive(path, Network.from_json(raw["network"]), codecs.Expansion.from_json(raw["expansion"]))


def decompress(spark: SparkSession, path: str, columns: list[str] | None = None) -> DataFrame:
    """All rows (of the named columns)."""
    archive = open_archive(spark, path)
    need = archive.expansion.needed(columns) if columns else None
    images = decode(archive.blocks(spark), archive.network, need)
    spec = archive.network.spec
    wide = images.select(*[a.restore().alias(a.name) for a in spec.attributes if need is None or a.name in need])
    return archive.expansion.collapse(wide, columns)


def lookup(spark: SparkSession, path: str, places: list[tuple[int, int]]) -> DataFrame:
    """The rows at (block_id, place in the block): reads those blocks and decodes those runs of codes only."""
    archive = open_archive(spark, path)
    asked: dict[int, list[int]] = {}
    for block, place in places:
        asked.setdefault(block, []).append(place)
    shared, names = spark.sparkContext.broadcast(archive.network.to_json()), archive.network.spec.names

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = Network.from_json(shared.value)
        for batch in batches:
            for row in batch.to_pylist():
                wanted = np.array(asked[row["block_id"]], np.int64)
                yield to_arrow(unpack(net, row["payload"], row["offsets"], row["nrows"], row["nbits"], row["delta"], wanted=wanted), net.spec, names)

    blocks = archive.blocks(spark).filter(F.col("block_id").isin(*asked))
    images = blocks.mapInArrow(found, archive.network.spec.image_schema())
    return archive.expansion.collapse(archive.network.spec.restored(images), None)


def archive_bytes(spark: SparkSession, archive: Archive) -> dict[str, int]:
    """Bytes of codes, index and model (deflated), as in a single file."""
    sums = archive.blocks(spark).agg(F.sum(F.octet_length("payload")), F.sum(F.octet_length("offsets")), F.sum("nrows"), F.sum("nbits")).first()
    model = zlib.compress(json.dumps({"network": archive.network.to_json()}).encode(), 9)
    return {"codes": int(sums[0] or 0), "index": int(sums[1] or 0), "model": len(model), "rows": int(sums[2] or 0), "code_bits": int(sums[3] or 0)}


def without_losing_edges(images: DataFrame, spec: TableSpec, structure: Structure) -> Structure:
    """Edges scored again on all rows: a node's parents are dropped if its objective is lower without them."""
    from relcodec.stats import node_objectives

    alone = Structure.empty(spec.names)
    with_parents = {r["node"]: r["objective"] for r in node_objectives(images, spec, structure).collect()}
    bare = {r["node"]: r["objective"] for r in node_objectives(images, spec, alone).collect()}
    return Structure({c: () if ps and bare[c] <= with_parents[c] else ps for c, ps in structure.parents.items()})


def with_options(options: Options, **changes) -> Options:
    return dataclasses.replace(options, **changes)

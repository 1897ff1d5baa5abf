"""What archives are compared with: general compressors, prefix codes, fixed widths and semantic compressors."""

from __future__ import annotations

import heapq
import math
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.baselines.held import HELD, HELD_KEYS, Held, as_values, landed
from relcodec.network import cells
from relcodec.schema import TableSpec, quoted
from relcodec.sources.stored import Stored, coded, line_texts, lines, mapped, texts_of, utf8


def text_sizes(df: DataFrame | Stored, groups: list[list[str]], codec: str = "gzip") -> list[int]:
    """Bytes of the text form of each group of columns, one compressed stream per group and partition, from one scan."""
    import bz2
    import lzma

    def stream():
        return {"gzip": lambda: zlib.compressobj(6, zlib.DEFLATED, 31), "zlib": lambda: zlib.compressobj(9), "bz2": bz2.BZ2Compressor, "lzma": lzma.LZMACompressor}[codec]()

    columns = list(dict.fromkeys(c for g in groups for c in g))
    places = [[columns.index(c) for c in g] for g in groups]

    def sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze, n, some = [stream() for _ in groups], [0] * len(groups), False
        for batch in batches:
            if not batch.num_rows:
                continue
            some = True
            texts = [line_texts(c) for c in batch.columns]
            for i, own in enumerate(places):
                n[i] += len(squeeze[i].compress(utf8(lines([texts[k] for k in own]))))
        if some:
            yield pa.RecordBatch.from_arrays([pa.array([k + len(x.flush())]) for k, x in zip(n, squeeze, strict=True)], names=names)

    names = [f"bytes{i}" for i in range(len(groups))]
    found = mapped(texts_of(df, columns), sizes, ", ".join(f"{n} long" for n in names)).agg(*[F.sum(n).alias(n) for n in names]).first()
    return [int(x or 0) for x in found]


def universal_size(df: DataFrame | Stored, codec: str = "gzip") -> int:
    """Bytes of the text form, one compressed stream per partition. codec: gzip, zlib, bz2 or lzma."""
    return text_sizes(df, [df.columns], codec)[0]


def huffman_lengths(counts: dict) -> dict:
    """Prefix-code length of each symbol; a single symbol still takes one bit."""
    if len(counts) == 1:
        return {k: 1 for k in counts}
    heap = [(n, i, [k]) for i, (k, n) in enumerate(sorted(counts.items(), key=lambda x: str(x[0])))]
    heapq.heapify(heap)
    length = dict.fromkeys(counts, 0)
    tick = len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for k in a[2] + b[2]:
            length[k] += 1
        heapq.heappush(heap, (a[0] + b[0], tick, a[2] + b[2]))
        tick += 1
    return length


def huffman_cost(counts: Iterable[tuple[int, int]]) -> int:
    """Bits of all rows under a prefix code, from (count, how many symbols have it): the sum of all merged weights.

    Symbols of one weight merge in pairs before any merged one of them is next, so they are taken together."""
    heap = [(n, many) for n, many in counts if n > 0]
    heapq.heapify(heap)
    if len(heap) == 1 and heap[0][1] == 1:
        return heap[0][0]
    bits = 0
    while heap:
        n, many = heapq.heappop(heap)
        while heap and heap[0][0] == n:
            many += heapq.heappop(heap)[1]
        if many > 1:
            bits += 2 * n * (many // 2)
            heapq.heappush(heap, (2 * n, many // 2))
            if many % 2:
                heapq.heappush(heap, (n, 1))
        elif heap:
            m, others = heapq.heappop(heap)
            bits += n + m
            heapq.heappush(heap, (n + m, 1))
            if others > 1:
                heapq.heappush(heap, (m, others - 1))
    return bits


def huffman_bits(df: DataFrame, column: str, parents: tuple[str, ...] = ()) -> int:
    """Bits of a column under one prefix code, or one per configuration of parents (the network with prefix codes).

    A code's bits follow from how many symbols occur how often, and n rows have at most sqrt(2 n) different counts, so
    no domain is collected."""
    by = [f"p{i}" for i in range(len(parents))]
    cells = df.groupBy(*[F.col(quoted(p)).cast("string").alias(c) for p, c in zip(parents, by, strict=True)], F.col(quoted(column)).cast("string").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    often = cells.groupBy(*by, "n").agg(F.count(F.lit(1)).alias("many"))
    if not parents:
        return huffman_cost((r["n"], r["many"]) for r in often.collect())

    return summed_costs(often.groupBy(*by).agg(F.collect_list(F.struct("n", "many")).alias("c")).select("c.n", "c.many"))


def summed_costs(groups: DataFrame) -> int:
    """Bits of prefix codes, one per row of (counts, how many symbols have each)."""
    def costs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ns, many = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([pa.array([huffman_cost(zip(n, m, strict=True)) for n, m in zip(ns, many, strict=True)], pa.int64())], names=["bits"])

    return int(groups.mapInArrow(costs, "bits long").agg(F.sum("bits")).first()[0] or 0)


def how_often(df: DataFrame | Stored, columns: list[str]) -> dict[str, list[tuple[int, int]]]:
    """(count, how many values occur so often) by column, from one scan: all that codes of single columns are reckoned from.
    NULL is a value, and values of one text are one. Of a stored table it is found once."""
    if isinstance(df, Stored):
        if not set(columns) <= set(df.often):
            df.often.update(counted_values(df, columns))
        return {c: df.often[c] for c in columns}
    return counted_values(df, columns)


def counted_values(df: DataFrame | Stored, columns: list[str]) -> dict[str, list[tuple[int, int]]]:
    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = Held(len(columns))
        for batch in batches:
            for i, column in enumerate(batch.columns):
                values, at = coded(column)
                n = np.bincount(at, minlength=len(values) + 1)
                yield from held.take(i, pa.concat_arrays([values, pa.nulls(1, values.type)]), np.zeros(len(n), np.int64), n)
        yield from held.rest()

    cells = mapped(texts_of(df, columns), counted, HELD).groupBy(*HELD_KEYS).agg(F.sum("n").alias("n"))
    found: dict[str, list[tuple[int, int]]] = {c: [] for c in columns}
    for r in cells.groupBy("i", "n").agg(F.count(F.lit(1)).alias("many")).collect():
        found[columns[r["i"]]].append((r["n"], r["many"]))
    return found


def column_huffman_delta_bits(df: DataFrame | Stored, columns: list[str]) -> float:
    """A prefix code per column, rows concatenated, sorted and delta coded."""
    often = how_often(df, columns)
    n = sum(n * many for n, many in often[columns[0]]) if columns else df.count()
    return sum(huffman_cost(often[c]) for c in columns) - (n * (math.log2(n) - 2) if n > 4 else 0)


def network_huffman_bits(df: DataFrame | Stored, parents: dict[str, tuple[str, ...]], spec: TableSpec | None = None) -> int:
    """Prefix codes per configuration of parents. spec: df holds the images of these attributes, all categorical; then
    their symbols are counted in one scan."""
    if spec is None or not parents:
        return sum(huffman_bits(df, c, ps) for c, ps in parents.items())
    often = cells(df, spec, list(parents.items())).groupBy("node", "key", "cnt").agg(F.count(F.lit(1)).alias("many"))
    return summed_costs(often.groupBy("node", "key").agg(F.collect_list(F.struct("cnt", "many")).alias("c")).select(F.col("c.cnt").alias("n"), "c.many"))


def domain_code_bits(df: DataFrame | Stored, columns: list[str]) -> DataFrame:
    """attribute, distinct_values, bits: fixed-width dictionary codes."""
    domains = {c: sum(many for _, many in x) for c, x in how_often(df, columns).items()}
    rows = [(c, k, math.ceil(math.log2(k))) for c, k in domains.items() if k]
    return df.sparkSession.createDataFrame(rows, "attribute string, distinct_values long, bits long")


def float32_bits(rows: int, columns: int) -> int:
    return 32 * rows * columns


def fixed_width_bits(lo: float, hi: float, precision: float) -> int:
    """Bits of a number on a grid of the given precision over its range."""
    return max(0, math.ceil(math.log2((hi - lo) / precision))) if hi > lo else 0


def parquet_size(df: DataFrame, path: str, compression: str = "snappy") -> int:
    df.write.mode("overwrite").option("compression", compression).parquet(path)
    return int(df.sparkSession.read.format("binaryFile").load(f"{path}/*.parquet").agg(F.sum("length")).first()[0])


def gzip_columns(df: DataFrame | Stored) -> int:
    """Bytes of the text form, each column compressed by itself."""
    return sum(text_sizes(df, [[c] for c in df.columns]))


def matches(column: pa.Array, value: pa.Scalar, tolerance: float | None) -> np.ndarray:
    """Which values are equal to one, or (numbers with a tolerance) near it; NULL is equal to NULL only."""
    if not value.is_valid:
        return column.is_null().to_numpy(zero_copy_only=False)
    if tolerance is not None:
        wide = column.type if pa.types.is_decimal(column.type) else pa.float64() if pa.types.is_floating(column.type) else pa.int64()
        found = pc.less_equal(pc.abs(pc.subtract(column.cast(wide), value.cast(wide))).cast(pa.float64()), tolerance)
    elif pa.types.is_floating(column.type) and np.isnan(value.as_py()):
        found = pc.is_nan(column)
    else:
        found = pc.equal(column, value)
    return pc.fill_null(found, False).to_numpy(zero_copy_only=False)


def representative_rows(df: DataFrame | Stored, spec: TableSpec, k: int = 8, rounds: int = 2, seed: int = 0) -> tuple[float, int]:
    """(bits, bytes after gzip) of rows as the nearest of k representatives and the attributes on which they differ by
    more than the tolerance.

    Each round assigns every row to the representative it matches on most attributes (the first of equal ones), then
    makes a representative of each group's modes and medians. The bits are representative ids, a flag per attribute, and
    fixed-width codes of what differs; the bytes are the same as compressed text. Rows are matched in Arrow batches, a
    batch's distinct values once each. Modes are exact, medians so up to a share of 2 / POINTS of a group's ranks.
    """
    names = spec.names
    plain = df.select(*[F.col(quoted(n)) for n in names])
    reps = plain.withColumn("_h", F.xxhash64(F.lit(seed), *[F.col(quoted(n)) for n in names])).orderBy("_h").limit(k).drop("_h").toArrow()
    if not reps.num_rows:
        return 0.0, 0
    # Values as `coded` has them, one array an attribute.
    reps = [values.take(pa.array(at, mask=at == len(values))) for values, at in (coded(c.combine_chunks()) for c in reps.columns)]
    sizes = {r["attribute"]: r["bits"] for r in domain_code_bits(df, names).collect()}
    near = {a.name for a in spec.attributes if a.numeric and a.kind not in ("timestamp", "date")}
    tolerances = [float(a.tolerance) if a.name in near else None for a in spec.attributes]
    raw = df.view({f"raw{i}": n for i, n in enumerate(names)}) if isinstance(df, Stored) else plain.toDF(*[f"raw{i}" for i in range(len(names))])

    def nearest(reps: list[pa.Array], columns: list[tuple[pa.Array, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        """(place of each row's representative, attribute by attribute whether rows match it)."""
        flags = np.empty((len(reps[0]), len(names), len(columns[0][1])), bool)
        for i, (values, at) in enumerate(columns):
            for j in range(len(reps[0])):
                flags[j, i] = np.append(matches(values, reps[i][j], tolerances[i]), not reps[i][j].is_valid)[at]
        own = flags.sum(axis=1, dtype=np.int32).argmax(axis=0)
        return own, np.take_along_axis(flags, own[None, None, :], axis=0)[0]

    for _ in range(rounds - 1):
        def assigned(batches: Iterator[pa.RecordBatch], reps: list[pa.Array] = reps) -> Iterator[pa.RecordBatch]:
            held, groups = Held(len(names) + 1, {i for i, n in enumerate(names) if n in near}), len(reps[0])
            for batch in batches:
                if not batch.num_rows:
                    continue
                columns = [coded(c) for c in batch.columns]
                own = nearest(reps, columns)[0]
                rows = np.bincount(own, minlength=groups)
                yield from held.take(len(names), pa.nulls(groups, pa.int64()), np.arange(groups), rows)
                for i, (values, at) in enumerate(columns):
                    n = np.bincount(own * (len(values) + 1) + at, minlength=groups * (len(values) + 1))
                    cell = np.flatnonzero(n)
                    rep, place = np.divmod(cell, len(values) + 1)
                    some = place < len(values)
                    yield from held.take(i, values.take(pa.array(place[some])), rep[some], n[cell[some]])
            yield from held.rest()

        made = mapped(raw, assigned, HELD).groupBy(*HELD_KEYS).agg(F.sum("n").alias("n")).persist()
        try:
            value = [F.col(c) for c in ("whole", "real", "bytes")]
            median = F.col("i").isin([i for i, n in enumerate(names) if n in near])
            modes = made.filter(~median).groupBy("i", "rep").agg(F.min(F.struct((-F.col("n")).alias("n"), *value)).alias("v")).select("i", "rep", "v.whole", "v.real", "v.bytes")
            upto = W.partitionBy("i", "rep").orderBy("whole", "real", "bytes").rowsBetween(W.unboundedPreceding, W.currentRow)
            ranked = made.filter(median).withColumns({"upto": F.sum("n").over(upto), "total": F.sum("n").over(W.partitionBy("i", "rep"))}).filter("2 * upto >= total")
            medians = ranked.groupBy("i", "rep").agg(F.min(F.struct(*value)).alias("v")).select("i", "rep", "v.whole", "v.real", "v.bytes")
            chosen = {(r["i"], r["rep"]): landed(r) for r in modes.unionByName(medians).collect()}
        finally:
            made.unpersist()
        groups = sorted(rep for i, rep in chosen if i == len(names))
        reps = [as_values([chosen.get((i, rep)) for rep in groups], x) for i, x in enumerate(reps)]

    def written(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze, size, n, lost = zlib.compressobj(6, zlib.DEFLATED, 31), 0, 0, np.zeros(len(names), np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            own, same = nearest(reps, [coded(c) for c in batch.columns[: len(names)]])
            n, lost = n + batch.num_rows, lost + (~same).sum(axis=1)
            texts = [pc.if_else(pa.array(same[i]), pa.scalar("", pa.large_string()), line_texts(batch.column(len(names) + i))) for i in range(len(names))]
            size += len(squeeze.compress(utf8(lines([pa.array(own + 1).cast(pa.large_string()), *texts]))))
        if n:
            yield pa.RecordBatch.from_pydict({"n": [n], "lost": [lost.tolist()], "bytes": [size + len(squeeze.flush())]})

    if isinstance(df, Stored) and df.text is not None:
        both = df.view({f"raw{i}": n for i, n in enumerate(names)} | {f"text{i}": df.text.get(n, n) for i, n in enumerate(names)})
    else:
        both = plain.select(*[F.col(quoted(n)).alias(f"raw{i}") for i, n in enumerate(names)], *[F.col(quoted(n)).cast("string").alias(f"text{i}") for i, n in enumerate(names)])
    parts = mapped(both, written, "n long, lost array<long>, bytes long").collect()
    rows, lost = sum(r["n"] for r in parts), [sum(x) for x in zip(*[r["lost"] for r in parts], strict=True)]
    bits = rows * (math.log2(max(len(reps[0]), 2)) + len(names)) + sum(n * sizes[a] for a, n in zip(names, lost, strict=True))
    return bits, sum(r["bytes"] for r in parts)


def tree_predictor_bits(df: DataFrame, spec: TableSpec, target: str, features: list[str], depth: int = 5) -> float:
    """Bits of one number predicted within its tolerance from others by a regression tree; misses are stored whole."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import DecisionTreeRegressor

    rows = VectorAssembler(inputCols=features, outputCol="_x", handleInvalid="skip").transform(df.select(*features, target))
    model = DecisionTreeRegressor(featuresCol="_x", labelCol=target, maxDepth=depth, seed=0).fit(rows)
    missed = model.transform(rows).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.abs(F.col("prediction") - F.col(target)) > spec[target].tolerance).alias("bad")).first()
    return missed["n"] + missed["bad"] * spec[target].depth + 64 * model.numNodes

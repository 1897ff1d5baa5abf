"""Scratch tables whose files tasks read themselves: columns go into Arrow without rows having been made of them."""

from __future__ import annotations

import string
from collections.abc import Callable, Iterator
from typing import Any
from urllib.parse import quote

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relcodec.codecs import Expansion
from relcodec.schema import LARGEST_CATEGORICAL, Attribute, TableSpec, infer_spec, quoted

#: Rows of a batch that a task reads.
READ_ROWS = 65_536
#: A column with more values than this in one task is no dictionary, and is looked at by Spark.
MOST_VALUES = 2 * LARGEST_CATEGORICAL
#: Columns that codecs take apart are looked up by value where they have at most so many.
MOST_LOOKED_UP = 1 << 20


class Stored:
    """A DataFrame of Parquet files, with a `mapInArrow` whose tasks open the files; all else is the DataFrame's.

    columns: what the files call the columns, by their names here (None: all of them, as they are). texts: columns of the
    files that hold others' texts as Spark writes them."""

    def __init__(self, df: DataFrame, columns: dict[str, str] | None = None, texts: dict[str, str] | None = None):
        self.table, self.names, self.text = df, columns, texts
        self.often: dict[str, list[tuple[int, int]]] = {}
        self.df = df if columns is None else df.select(*[F.col(quoted(c)).alias(n) for n, c in columns.items()])
        # Spark leaves letters beyond ASCII in its paths, which pyarrow wants written like blanks.
        self.files = sorted(quote(f, safe=string.printable) for f in df.inputFiles())

    def __getattr__(self, name: str) -> Any:
        return getattr(self.df, name)

    def view(self, columns: dict[str, str]) -> Stored:
        """The same files under other columns."""
        return Stored(self.table, columns)

    def openable(self) -> bool:
        """Whether pyarrow finds the files, wherever they lie; else Spark reads them."""
        from pyarrow import fs

        try:
            return all(system.get_file_info(path).is_file for system, path in map(fs.FileSystem.from_uri, self.files))
        except (OSError, ValueError, pa.ArrowException):
            return False

    def mapInArrow(self, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: T.StructType | str, encoded: bool = False) -> DataFrame:  # noqa: N802
        """encoded: texts may come as dictionary arrays."""
        if not self.openable():
            return self.df.mapInArrow(work, schema)
        spark = self.df.sparkSession
        files, names = self.files, self.names
        tasks = max(1, min(len(files), spark.sparkContext.defaultParallelism))
        texts = [f.name for f in self.table.schema.fields if encoded and isinstance(f.dataType, T.StringType)]

        def read(numbers: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import pyarrow.parquet as pq
            from pyarrow import fs

            def rows() -> Iterator[pa.RecordBatch]:
                for batch in numbers:
                    for task in batch.column(0).to_pylist():
                        for uri in files[len(files) * task // tasks: len(files) * (task + 1) // tasks]:
                            system, path = fs.FileSystem.from_uri(uri)
                            with system.open_input_file(path) as f:
                                file = pq.ParquetFile(f, read_dictionary=texts, coerce_int96_timestamp_unit="us")
                                for rows in file.iter_batches(READ_ROWS, columns=None if names is None else list(dict.fromkeys(names.values())), use_threads=False):
                                    yield rows if names is None else pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index(c)) for c in names.values()], names=list(names))

            return work(rows())

        return spark.range(0, tasks, 1, tasks).mapInArrow(read, schema)


    def drawn(self, numbers: dict[str, Column], keep: Column) -> DataFrame:
        """The rows that a condition on seeded numbers keeps, with these numbers."""
        return self.df.withColumns(numbers).filter(keep)


class Derived(Stored):
    """Images of a stored table that tasks make of its columns as they read them; `df` is what Spark makes of them.

    plan: for each attribute the column of the files and, of columns that a codec takes apart, the place in `parts`, which
    holds (values, images of each value)."""

    def __init__(self, stored: Stored, expansion: Expansion, spec: TableSpec, plan: list[tuple[str, int | None]], parts: list[tuple[pa.Array, pa.Array]]):
        super().__init__(stored.table, {f"from{i}": c for i, (c, _) in enumerate(plan)})
        self.rows, self.source, self.expansion, self.spec = stored.df, self.view(self.names), expansion, spec
        self.places, self.parts = [k for _, k in plan], parts
        self.df = spec.images(expansion.expand(stored.df))

    def mapInArrow(self, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: T.StructType | str, encoded: bool = False) -> DataFrame:  # noqa: N802
        if not self.openable():
            return self.df.mapInArrow(work, schema)
        spec, places, shared = self.spec, self.places, self.df.sparkSession.sparkContext.broadcast(self.parts)

        def images(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                columns = [image_of(a, c, None if k is None else shared.value[k]) for a, c, k in zip(spec.attributes, batch.columns, places, strict=True)]
                yield pa.RecordBatch.from_arrays(columns, names=spec.names)

        return self.source.mapInArrow(lambda batches: work(images(batches)), schema, encoded=True)

    def drawn(self, numbers: dict[str, Column], keep: Column) -> DataFrame:
        rows = self.rows.withColumns(numbers).filter(keep)
        wide = Expansion([*self.expansion.columns, *((n, "double", None, {}) for n in numbers)]).expand(rows)
        return wide.select(*[a.image().alias(a.name) for a in self.spec.attributes], *numbers)


def image_of(a: Attribute, column: pa.Array, known: tuple[pa.Array, pa.Array] | None) -> pa.Array:
    """What `Attribute.image` gives, of a column's own values or of its text, or (values, images) looked up."""
    values, at = coded(column)
    if known is not None:
        # A NULL is among the values, too.
        found = known[1].take(pc.index_in(pa.concat_arrays([values, pa.nulls(1, values.type)]), known[0]))
    elif not a.numeric:
        found = pa.concat_arrays([values.cast(pa.string()), pa.nulls(1, pa.string())])
    else:
        whole = values.to_numpy(zero_copy_only=False)
        whole = np.rint(whole * 10**a.scale).astype(np.int64) if a.kind == "decimal" else whole.astype(np.int64)
        found = pa.concat_arrays([pa.array((whole - a.image_lo) // a.step), pa.nulls(1, pa.int64())])
    return found.take(pa.array(at))


def derived(stored: Stored, expansion: Expansion, specs: list[TableSpec]) -> list[Derived] | None:
    """The images of a table with its texts under several specs, where tasks can make them; else None."""
    from relcodec.baselines import how_often

    types = {f.name: f.dataType for f in stored.df.schema.fields}
    apart = {c[0]: c for c in expansion.columns if c[2] is not None}
    if stored.text is None or any(not isinstance(types[n], T.StringType) for n in apart):
        return None
    if apart:
        often = how_often(stored, stored.df.columns)
        if any(sum(many for _, many in often[n]) > MOST_LOOKED_UP for n in apart):
            return None
    looked_up: dict[str, tuple[DataFrame, str]] = {}
    for n, c in apart.items():
        values = stored.df.select(F.col(quoted(n))).distinct().persist()
        looked_up |= {x: (values, n) for x in Expansion([c]).expand(values).columns}
    out = []
    try:
        for spec in specs:
            plan: list[tuple[str, int | None]] = []
            parts: list[tuple[pa.Array, pa.Array]] = []
            for a in spec.attributes:
                if a.name in looked_up:
                    values, n = looked_up[a.name]
                    image = Expansion([apart[n], ("_of", "string", None, {})]).expand(values.withColumn("_of", F.col(quoted(n)))).select("_of", a.image().alias("image")).toArrow()
                    plan.append((n, len(parts)))
                    parts.append((image.column("_of").combine_chunks(), image.column("image").combine_chunks()))
                elif a.kind in ("categorical", "string") and a.dtype != "binary":
                    plan.append((stored.text.get(a.name, a.name), None))
                elif a.kind == "integer" or a.kind == "decimal" and a.dtype == "double":
                    plan.append((a.name, None))
                else:
                    return None
            out.append(Derived(stored, expansion, spec, plan, parts))
    finally:
        for values, _ in looked_up.values():
            values.unpersist()
    return out


def text_columns(df: DataFrame) -> dict[str, str]:
    """Names of the columns that `with_texts` adds, by the columns whose texts only Spark writes as it does."""
    plain = (T.StringType, T.ByteType, T.ShortType, T.IntegerType, T.LongType)
    return {f.name: f"_text{i}" for i, f in enumerate(df.schema.fields) if not isinstance(f.dataType, plain)}


def with_texts(df: DataFrame) -> DataFrame:
    """df and the texts of its columns, as far as they are neither texts nor whole numbers themselves."""
    return df.select("*", *[F.col(quoted(c)).cast("string").alias(t) for c, t in text_columns(df).items()])


def texts_of(df: DataFrame | Stored, columns: list[str]) -> DataFrame | Stored:
    """The texts of columns, NULL as NULL: text0, text1, and so on. (Of a stored table whole numbers come as they are.)"""
    if isinstance(df, Stored) and df.text is not None:
        return df.view({f"text{i}": df.text.get(c, c) for i, c in enumerate(columns)})
    df = df.df if isinstance(df, Stored) else df
    return df.select(*[F.col(quoted(c)).cast("string").alias(f"text{i}") for i, c in enumerate(columns)])


def mapped(df: DataFrame | Stored, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: T.StructType | str) -> DataFrame:
    """mapInArrow of work that takes dictionary arrays."""
    return df.mapInArrow(work, schema, encoded=True) if isinstance(df, Stored) else df.mapInArrow(work, schema)


def coded(column: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """(distinct values, the place among them of each row's value): NULL is one place after the last. Times are
    microseconds."""
    if pa.types.is_timestamp(column.type):
        column = column.cast(pa.timestamp("us", column.type.tz)).view(pa.int64())
    made = column if pa.types.is_dictionary(column.type) else column.dictionary_encode()
    return made.dictionary, pc.fill_null(made.indices, len(made.dictionary)).to_numpy(zero_copy_only=False).astype(np.int64)


def line_texts(column: pa.Array) -> pa.Array:
    """A column of `texts_of` in full, NULL as an empty text."""
    values, at = coded(column)
    return pa.concat_arrays([values.cast(pa.large_string()), pa.array([""], pa.large_string())]).take(pa.array(at))


def utf8(texts: pa.Array) -> memoryview:
    """The bytes of large texts, one after the other."""
    _, places, data = texts.buffers()
    if data is None or not len(texts):
        return memoryview(b"")
    at = np.frombuffer(places, np.int64)[texts.offset: texts.offset + len(texts) + 1]
    return memoryview(data)[int(at[0]): int(at[-1])]


def lines(columns: list[pa.Array]) -> pa.Array:
    """Texts put together by commas, with a line end each."""
    one = columns[0] if len(columns) == 1 else pc.binary_join_element_wise(*columns, pa.scalar(",", pa.large_string()))
    return pc.binary_join_element_wise(one, pa.scalar("", pa.large_string()), pa.scalar("\n", pa.large_string()))


def values_of(stored: Stored) -> tuple[DataFrame, list[str]]:
    """(a kept table with every value of each column that has few in all tasks, with repetitions; these columns)."""
    plain = [f for f in stored.df.schema.fields if isinstance(f.dataType, (T.StringType, T.IntegerType, T.LongType, T.DoubleType))]
    schema = T.StructType([*(T.StructField(f.name, f.dataType) for f in plain), T.StructField("_many", T.ArrayType(T.IntegerType()))])

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Array | None] = [None] * len(plain)
        many: set[int] = set()
        for batch in batches:
            for i, f in enumerate(plain):
                if i in many or not batch.num_rows:
                    continue
                column = batch.column(batch.schema.get_field_index(f.name))
                # Doubles are told apart by their bits: NaN and the zeros' signs stay.
                column = column.view(pa.int64()) if isinstance(f.dataType, T.DoubleType) else column
                own = column.unique()
                held[i] = own if held[i] is None else pa.chunked_array([held[i], own]).unique()
                if len(held[i]) > MOST_VALUES:
                    many.add(i)
                    held[i] = held[i][:1]
        if held and held[0] is not None:
            size = max(map(len, held))
            # A column's first value is repeated, which no minimum, dictionary or count of distinct values sees.
            full = [h.take(pa.array(np.where(np.arange(size) < len(h), np.arange(size), 0))) for h in held]
            full = [h.view(pa.float64()) if isinstance(f.dataType, T.DoubleType) else h for h, f in zip(full, plain, strict=True)]
            yield pa.RecordBatch.from_arrays([*full, pa.array([sorted(many)] * size, pa.list_(pa.int32()))], names=schema.names)

    if not plain:
        return stored.df.limit(0).persist(), []
    table = stored.mapInArrow(found, schema).persist()
    many = {r["i"] for r in table.select(F.explode("_many").alias("i")).distinct().collect()}
    return table, [f.name for i, f in enumerate(plain) if i not in many]


def stored_spec(df: DataFrame, expansion: Expansion, rows: int) -> TableSpec:
    """`infer_spec` of the expanded table: columns of few values are looked at through their values, the others in full."""
    values, few = values_of(Stored(df))
    part = lambda source, names: infer_spec(Expansion([c for c in expansion.columns if c[0] in names]).expand(source), rows=rows).attributes if names else ()
    many = [n for n in df.columns if n not in few]
    made = {a.name: a for a in (*part(values, few), *part(df.select(*[F.col(quoted(n)) for n in many]), many))}
    values.unpersist()
    return TableSpec(tuple(made[n] for n in expansion.expand(df).columns))

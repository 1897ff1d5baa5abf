"""Typed attributes of a table, and their integer or string images that the coder works on.

An image is a Catalyst expression: a string for categorical values (NULL stays NULL), a leaf number for numbers, the
text itself for strings. `restore` is its inverse up to the tolerance.
"""

from __future__ import annotations

import dataclasses
import json
import struct
from dataclasses import dataclass, field
from decimal import Decimal

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

MAX_CATEGORICAL = 4096
LARGEST_CATEGORICAL = 1 << 15
#: Ranges of images from here on would leave 64 bits in between; such numbers travel as text.
WIDEST = 1 << 62
#: Bit patterns of 32-bit floats are multiples of this among those of doubles.
FLOAT_UNIT = 1 << 29


@dataclass(frozen=True)
class Attribute:
    """kind: categorical, integer, decimal (scale), timestamp (unit in microseconds), date, real (unit: what all bit
    patterns are multiples of), string (texts, and values of any type that no number image holds exactly) or user (with
    the class of its model)."""

    name: str
    kind: str
    dtype: str
    lo: float | int = 0
    hi: float | int = 0
    scale: int = 0
    unit: int = 1
    tolerance: float = 0.0
    nullable: bool = False
    dictionary: tuple[str | None, ...] = field(default=())
    model: str = ""
    number: str = ""  # of a categorical attribute: its kind under a tolerance

    @property
    def numeric(self) -> bool:
        return self.kind in ("integer", "decimal", "timestamp", "date", "real")

    @property
    def measured(self) -> str | None:
        """The kind under a tolerance, of what can have one: also doubles whose exact images are too wide."""
        return self.kind if self.numeric else "real" if self.kind == "string" and self.dtype in ("double", "float") and self.hi > self.lo else None

    def within(self, tolerance: float, named: bool) -> Attribute:
        """The attribute under a tolerance. Categories keep their exact values, unless the attribute is named: then they
        are numbers, however few values occur."""
        if self.number and named and tolerance > 0:
            return dataclasses.replace(self, kind=self.number, tolerance=tolerance, dictionary=(), number="")
        return dataclasses.replace(self, kind=self.measured, tolerance=tolerance) if self.measured else self

    @property
    def grid(self) -> bool:
        """Whether leaves are cells of equal width over doubles; else they are runs of integer images."""
        return self.kind == "real" and self.tolerance > 0

    @property
    def bitwise(self) -> bool:
        """Whether the image is the number itself, whose bits the coder reads: doubles without a tolerance."""
        return self.kind == "real" and not self.grid

    @property
    def step(self) -> int:
        """Integer images per leaf: the widest run whose middle is within the tolerance of all of it."""
        scale = {"decimal": 10.0**self.scale, "timestamp": 1.0 / self.unit}.get(self.kind, 1.0)
        return 1 if self.kind == "real" else int(2 * self.tolerance * scale + 1e-9) + 1

    @property
    def leaves(self) -> int:
        if self.grid:
            return max(1, int(-(-(self.hi - self.lo) // (2 * self.tolerance))))
        return (self.image_hi - self.image_lo) // self.step + 1

    @property
    def image_lo(self) -> int:
        return ordered_int(self.lo) // self.unit if self.kind == "real" else int(self.lo)

    @property
    def image_hi(self) -> int:
        return ordered_int(self.hi) // self.unit if self.kind == "real" else int(self.hi)

    @property
    def depth(self) -> int:
        return (self.leaves - 1).bit_length()

    def integer_image(self, c: Column) -> Column:
        if self.kind == "decimal":
            return (c * F.lit(10**self.scale) if self.dtype.startswith("decimal") else F.round(c * 10**self.scale)).cast("long")
        if self.kind == "timestamp":
            return F.expr(f"{micros(self.name, self.dtype)} div {self.unit}L")
        if self.kind == "date":
            return F.unix_date(c).cast("long")
        return c.cast("long")

    def image(self) -> Column:
        c = F.col(quoted(self.name))
        if self.kind == "categorical":
            return c.cast("string")
        if self.kind in ("string", "user"):
            return F.base64(c) if self.dtype == "binary" else c.cast("string")
        if self.grid:
            x = F.ceil((c.cast("double") - F.lit(float(self.lo))) / (2 * self.tolerance)).cast("long") - 1
            return F.least(F.greatest(x, F.lit(0).cast("long")), F.lit(self.leaves - 1).cast("long"))
        if self.bitwise:
            return c.cast("double")
        d = self.integer_image(c) - F.lit(self.image_lo).cast("long")
        return d if self.step == 1 else F.call_function("div", d, F.lit(self.step).cast("long"))

    def restore(self) -> Column:
        c = F.col(quoted(self.name))
        if self.kind in ("categorical", "string", "user"):
            return F.unbase64(c) if self.dtype == "binary" else F.lit(None).cast("void") if self.dtype == "void" else c.cast(self.dtype)
        if self.bitwise:
            return c.cast(self.dtype)
        if self.grid:
            return (F.lit(float(self.lo)) + (c + 0.5) * (2 * self.tolerance)).cast(self.dtype)
        v = c * self.step + F.lit(self.image_lo).cast("long")
        v = v + (self.step - 1) // 2 if self.step > 1 else v
        if self.kind == "decimal" and self.dtype.startswith("decimal"):
            return (v.cast("decimal(19,0)") * F.lit(Decimal(1).scaleb(-self.scale))).cast(self.dtype)
        if self.kind == "decimal":
            return (v / 10**self.scale).cast(self.dtype)
        if self.kind == "timestamp":
            if self.dtype == "timestamp_ntz":
                seconds = (v * self.unit).cast("decimal(24,0)") / 1_000_000
                return F.expr("TIMESTAMP_NTZ '1970-01-01 00:00:00'") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), seconds.cast("decimal(18,6)"))
            return F.timestamp_micros(v * self.unit).cast(self.dtype)
        if self.kind == "date":
            return F.date_from_unix_date(v.cast("int"))
        return v.cast(self.dtype)

    def leaf(self, c: Column) -> Column:
        """The leaf number of an image column."""
        return F.shiftright(ordered_bits(c), self.unit.bit_length() - 1) - F.lit(self.image_lo).cast("long") if self.bitwise else c

    def leaves_of(self, x: np.ndarray) -> np.ndarray:
        """Leaf numbers of doubles: their bits in an order-keeping form, counted from the smallest."""
        bits = np.where(x == 0, 0.0, x).astype(np.float64).view(np.int64)
        ordered = np.where(bits < 0, -(bits & np.int64(2**63 - 1)) - 1, bits)
        return (ordered >> (self.unit.bit_length() - 1)) - self.image_lo

    def doubles_of(self, leaf: np.ndarray) -> np.ndarray:
        """The inverse of leaves_of."""
        v, low = leaf + self.image_lo, self.unit.bit_length() - 1
        magnitude = np.where(v < 0, -v - 1, v) << low
        return np.where(v < 0, magnitude | np.int64(-(2**63)), magnitude).view(np.float64)


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def micros(name: str, dtype: str) -> str:
    """SQL for microseconds since 1970; of a timestamp without zone by its own clock, whatever the session's zone."""
    q = quoted(name)
    if dtype != "timestamp_ntz":
        return f"unix_micros({q})"
    return f"(unix_date(cast({q} as date)) * 86400000000L + hour({q}) * 3600000000L + minute({q}) * 60000000L + cast(extract(SECOND FROM {q}) * 1000000 as bigint))"


def ordered_int(x: float) -> int:
    """What ordered_bits gives, on the driver."""
    bits = struct.unpack("<q", struct.pack("<d", abs(x)))[0] if abs(x) >= 2.0**-1000 else 0
    return -bits - 1 if x < 0 and bits else bits


def ordered_bits(c: Column) -> Column:
    """The bits of a finite double as an integer that sorts like it; both zeros are one, subnormal numbers become zero."""
    # A double is rebuilt from sign, exponent and fraction, all exact in double arithmetic.
    d = c.cast("double")
    a = F.abs(d)
    guess = F.floor(F.log2(a)).cast("int")
    e = F.when(F.pow(F.lit(2.0), guess) > a, guess - 1).when(F.pow(F.lit(2.0), guess + 1) <= a, guess + 1).otherwise(guess)
    fraction = ((a / F.pow(F.lit(2.0), e) - 1.0) * float(1 << 52)).cast("long")
    magnitude = F.when(a < 2.0**-1000, F.lit(0).cast("long")).otherwise((e + 1023).cast("long") * F.lit(1 << 52).cast("long") + fraction)
    return F.when((d < 0) & (magnitude > 0), -magnitude - 1).otherwise(magnitude)


@dataclass(frozen=True)
class TableSpec:
    attributes: tuple[Attribute, ...]

    def __getitem__(self, name: str) -> Attribute:
        return next(a for a in self.attributes if a.name == name)

    @property
    def names(self) -> list[str]:
        return [a.name for a in self.attributes]

    def with_tolerance(self, tolerance: float, names: list[str] | None = None) -> TableSpec:
        """Numbers (or the named ones) within `tolerance`."""
        return TableSpec(tuple(a.within(tolerance, names is not None) if names is None or a.name in names else a for a in self.attributes))

    def with_tolerance_pct(self, percent: float, names: list[str] | None = None) -> TableSpec:
        """Numbers within a share of their range."""
        def span(a: Attribute) -> float:
            kind = a.number or a.kind
            return (a.hi - a.lo) / {"decimal": 10.0**a.scale}.get(kind, 1.0) * (a.unit if kind == "timestamp" else 1)
        return TableSpec(tuple(a.within(span(a) * percent / 100, names is not None) if names is None or a.name in names else a for a in self.attributes))

    def with_model(self, name: str, model: type) -> TableSpec:
        """A column under a user type (`usertypes.Model`)."""
        named = f"{model.__module__}:{model.__qualname__}"
        return TableSpec(tuple(Attribute(a.name, "user", a.dtype, nullable=a.nullable, model=named) if a.name == name else a for a in self.attributes))

    def images(self, df: DataFrame) -> DataFrame:
        return df.select(*[a.image().alias(a.name) for a in self.attributes])

    def restored(self, images: DataFrame) -> DataFrame:
        return images.select(*[a.restore().alias(a.name) for a in self.attributes])

    def quantise(self, df: DataFrame) -> DataFrame:
        """What a round trip through the archive gives."""
        return self.restored(self.images(df))

    def image_schema(self, names: list[str] | None = None) -> str:
        return ", ".join(f"{quoted(a.name)} {'double' if a.bitwise else 'long' if a.numeric else 'string'}" for a in self.attributes if names is None or a.name in names)

    def to_json(self) -> str:
        return json.dumps([dataclasses.asdict(a) for a in self.attributes])

    @classmethod
    def from_json(cls, text: str) -> TableSpec:
        return cls(tuple(Attribute(**a | {"dictionary": tuple(a["dictionary"])}) for a in json.loads(text)))


def spec_of(f: T.StructField, r, base: dict) -> Attribute:
    """The attribute of a column without a dictionary, from its range."""
    text = Attribute(kind="string", **base)
    if isinstance(f.dataType, (T.DoubleType, T.FloatType)) and not r["odd"]:
        scale = next((s for s in (0, 1, 2) if r[f"scale{s}"]), None)
        if scale is not None:
            return Attribute(kind="decimal", scale=scale, lo=round(r["lo"] * 10**scale), hi=round(r["hi"] * 10**scale), **base)
        real = Attribute(kind="real", lo=r["lo"], hi=r["hi"], unit=FLOAT_UNIT if r["single"] else 1, **base)
        return real if real.image_hi - real.image_lo < 2**63 - 1 else dataclasses.replace(text, lo=r["lo"], hi=r["hi"])
    if isinstance(f.dataType, T.DecimalType) and f.dataType.precision <= 18:
        return Attribute(kind="decimal", scale=f.dataType.scale, lo=int(r["lo"].scaleb(f.dataType.scale)), hi=int(r["hi"].scaleb(f.dataType.scale)), **base)
    if isinstance(f.dataType, (T.TimestampType, T.TimestampNTZType)):
        unit = 86_400_000_000 if r["days"] else 1_000_000 if r["seconds"] else 1
        return Attribute(kind="timestamp", unit=unit, lo=r["lo"] // unit, hi=r["hi"] // unit, **base)
    if isinstance(f.dataType, (T.DateType, T.IntegralType)) and r["hi"] - r["lo"] < WIDEST:
        return Attribute(kind="date" if isinstance(f.dataType, T.DateType) else "integer", lo=r["lo"], hi=r["hi"], **base)
    return text


def infer_spec(df: DataFrame, max_categorical: int = MAX_CATEGORICAL, categorical: tuple[str, ...] = (), rows: int | None = None) -> TableSpec:
    """Kinds and domains from the data: one aggregate for ranges, one for the dictionaries of small domains.

    A double is decimal if every value is a multiple of 1, 0.1 or 0.01, a timestamp counts days, seconds or
    microseconds. Numbers that an image would not give back exactly (NaN, infinities, a negative zero, subnormal
    doubles, decimals of over 18 digits, ranges of 2^62) travel as text, bytes in base 64. Nested types must be taken
    apart before (`codecs.Expansion`); types without a text form are an error. Dictionaries hold at most max_categorical (and never over 2^15) values, so the driver's share is bounded.
    Nothing depends on how often a value occurs but the number of rows, which `rows` gives where df holds the values only.
    """
    asked = [F.count(F.lit(1)).alias("_rows")]
    for f in df.schema.fields:
        if not isinstance(f.dataType, (T.NumericType, T.StringType, T.BooleanType, T.BinaryType, T.DateType, T.TimestampType, T.TimestampNTZType, T.NullType)):
            raise TypeError(f"column {f.name}: an archive cannot hold the type {f.dataType.simpleString()}")
        c = F.col(quoted(f.name))
        one = [F.count(F.when(c.isNull(), 1)).alias("nulls"), F.approx_count_distinct(c).alias("distinct")]
        if isinstance(f.dataType, (T.DoubleType, T.FloatType)):
            d = c.cast("double")
            one += [F.min(d).alias("lo"), F.max(d).alias("hi")]
            one += [F.bool_and(((F.rint(d * 10**s) / 10**s) == d) & (F.abs(d) < 1e13)).alias(f"scale{s}") for s in (0, 1, 2)]
            one.append(F.bool_or(F.isnan(d) | (F.abs(d) == float("inf")) | ((d == 0) & d.cast("string").startswith("-")) | ((d != 0) & (F.abs(d) < 2.0**-1000))).alias("odd"))
            one.append(F.bool_and(d.cast("float").cast("double") == d).alias("single"))
        elif isinstance(f.dataType, T.DecimalType):
            one += [F.min(c).alias("lo"), F.max(c).alias("hi")]
        elif isinstance(f.dataType, (T.TimestampType, T.TimestampNTZType)):
            m = F.expr(micros(f.name, f.dataType.simpleString()))
            one += [F.min(m).alias("lo"), F.max(m).alias("hi"), F.bool_and(F.pmod(m, F.lit(86_400_000_000)) == 0).alias("days"), F.bool_and(F.pmod(m, F.lit(1_000_000)) == 0).alias("seconds")]
        elif isinstance(f.dataType, T.DateType):
            one += [F.min(F.unix_date(c)).alias("lo"), F.max(F.unix_date(c)).alias("hi")]
        elif isinstance(f.dataType, T.IntegralType):
            one += [F.min(c.cast("long")).alias("lo"), F.max(c.cast("long")).alias("hi")]
        asked.append(F.struct(*one).alias(f.name))
    found = df.agg(*asked).first()
    kinds: dict[str, Attribute] = {}
    small = []
    for f in df.schema.fields:
        r = found[f.name]
        base = {"name": f.name, "dtype": f.dataType.simpleString(), "nullable": r["nulls"] > 0}
        few = max(64, (found["_rows"] if rows is None else rows) / 4)
        if f.name in categorical or r["distinct"] <= min(max_categorical, LARGEST_CATEGORICAL, few) * 0.95 and not isinstance(f.dataType, T.BinaryType):
            small.append(f.name)
            continue
        kinds[f.name] = spec_of(f, r, base)
    if small:
        sets = F.struct(*[F.array_sort(F.collect_set(F.col(quoted(n)).cast("string"))).alias(n) for n in small])
        values = df.agg(sets.alias("s")).first()["s"]
        for n in small:
            f = df.schema[n]
            nulls = found[n]["nulls"] > 0
            base = {"name": n, "dtype": f.dataType.simpleString(), "nullable": nulls}
            number = spec_of(f, found[n], base) if values[n] else Attribute(kind="string", **base)
            base |= {"number": number.measured, "lo": number.lo, "hi": number.hi, "scale": number.scale, "unit": number.unit} if number.measured else {}
            kinds[n] = Attribute(kind="categorical", dictionary=((None,) if nulls else ()) + tuple(values[n]), **base)
    return TableSpec(tuple(kinds[f.name] for f in df.schema.fields))

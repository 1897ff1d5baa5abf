"""User-defined types: a codec takes a column apart into plain columns before coding, and puts it together again.

A codec's parts are coded like any attribute, so they can depend on others and be depended on. Values that a codec
would not give back exactly travel whole in one more, mostly NULL, part. Codecs are Catalyst expressions; register your
own with `register_codec`.
"""

from __future__ import annotations

import json
from collections import Counter
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relcodec.schema import quoted

REGISTRY: dict[str, type] = {}


def register_codec(name: str, codec: type) -> None:
    REGISTRY[name] = codec


class Codec:
    """split: part name -> column; join: the inverse. `detect` says whether a sample of values suits, and with what parameters."""

    def __init__(self, **params):
        self.params = params

    @classmethod
    def detect(cls, values: list) -> dict | None:
        return None

    def split(self, c: Column) -> dict[str, Column]:
        raise NotImplementedError

    def join(self, parts: dict[str, Column]) -> Column:
        raise NotImplementedError


class TemplateId(Codec):
    """A fixed prefix and a zero-padded number, such as Customer#000000042."""

    @classmethod
    def detect(cls, values):
        import re

        found = [re.fullmatch(r"([^0-9]*)([0-9]{1,17})", v) for v in values]
        if not values or not all(found) or len({m[1] for m in found}) != 1:
            return None
        widths = {len(m[2]) for m in found}
        return {"prefix": found[0][1], "width": widths.pop() if len(widths) == 1 else 1}

    def split(self, c):
        # What stands behind the prefix, if it is a number of at most 17 digits; `join` tells whether it is all of the text.
        number = F.substr(c, F.lit(len(self.params["prefix"]) + 1)).try_cast("long")
        return {"number": F.when(number.between(0, 10**17 - 1), number)}

    def join(self, parts):
        digits = parts["number"].cast("string")
        padded = F.lpad(digits, F.greatest(F.length(digits), F.lit(self.params["width"])), F.lit("0"))
        return F.concat(F.lit(self.params["prefix"]), padded)


class JsonFlat(Codec):
    """A flat JSON object whose members are whole numbers, always the same keys in the same order."""

    @classmethod
    def detect(cls, values):
        try:
            objects = [json.loads(v) for v in values]
        except ValueError:
            return None
        if not objects or not all(isinstance(o, dict) and o and all(type(x) is int for x in o.values()) for o in objects) or len({tuple(o) for o in objects}) != 1:
            return None
        return {"keys": list(objects[0])}

    def split(self, c):
        return {k: F.get_json_object(c, f"$.{k}").try_cast("long") for k in self.params["keys"]}

    def join(self, parts):
        members = [F.concat(F.lit((", " if i else "{") + json.dumps(k) + ": "), parts[k].cast("string")) for i, k in enumerate(self.params["keys"])]
        # NULL if any member is: a NULL text must not come back as an object.
        return F.concat(*members, F.lit("}"))


class Url(Codec):
    """Scheme, host, directory, last number and what follows."""

    PATTERN = r"^([a-z]+)://([^/]+)(/.*?)([0-9]{0,9})([^0-9]*)$"

    @classmethod
    def detect(cls, values):
        return {} if values and all("://" in v for v in values) else None

    def split(self, c):
        part = lambda i: F.regexp_extract(c, self.PATTERN, i)
        return {"scheme": part(1), "host": part(2), "directory": part(3), "number": F.when(part(4).rlike("^(0|[1-9][0-9]*)$"), part(4)).try_cast("long"), "tail": part(5)}

    def join(self, parts):
        return F.concat(parts["scheme"], F.lit("://"), parts["host"], parts["directory"], F.coalesce(parts["number"].cast("string"), F.lit("")), parts["tail"])


class FloatVector(Codec):
    """An array of numbers of one length (the most frequent of the sample): a column per coordinate."""

    @classmethod
    def detect(cls, values):
        sizes = Counter(len(v) for v in values)
        return {"dim": sizes.most_common(1)[0][0] if sizes else 0}

    def split(self, c):
        return {f"e{i}": F.get(c, i).cast("double") for i in range(self.params["dim"])}

    def join(self, parts):
        return F.array(*[parts[f"e{i}"].cast(self.params.get("type", "float")) for i in range(self.params["dim"])])


class Nested(Codec):
    """A struct, map or array of anything but numbers: its values travel whole, as JSON."""

    def split(self, c):
        return {}

    def join(self, parts):
        return F.lit(None)


def json_safe(t: T.DataType) -> bool:
    """Whether values of a nested type come back from JSON exactly."""
    if isinstance(t, T.ArrayType):
        return json_safe(t.elementType)
    if isinstance(t, T.MapType):
        return isinstance(t.keyType, T.StringType) and json_safe(t.valueType)
    if isinstance(t, T.StructType):
        return len({f.name.lower() for f in t.fields}) == len(t.fields) and all(json_safe(f.dataType) for f in t.fields)
    return isinstance(t, (T.NumericType, T.StringType, T.BooleanType, T.BinaryType, T.DateType, T.TimestampType, T.TimestampNTZType))


#: Formats that keep microseconds.
JSON = {"timestampFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSSXXX", "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS", "timeZone": "UTC"}

for _name, _codec in (("template", TemplateId), ("json", JsonFlat), ("url", Url), ("vector", FloatVector), ("nested", Nested)):
    register_codec(_name, _codec)


@dataclass
class Expansion:
    """Which columns are taken apart by which codec. Parts are named column__part; `raw` holds misfits."""

    columns: list[tuple[str, str, str | None, dict]]  # name, type, codec or None, parameters

    @classmethod
    def none(cls, df: DataFrame) -> Expansion:
        return cls([(f.name, f.dataType.simpleString(), None, {}) for f in df.schema.fields])

    @classmethod
    def infer(cls, df: DataFrame, probe: int = 200, codecs: dict[str, str] | None = None) -> Expansion:
        """Codecs by a look at up to `probe` rows; what does not suit all other rows goes into `raw`."""
        rows = df.limit(probe).collect()
        out = []
        for f in df.schema.fields:
            chosen, params = (codecs or {}).get(f.name), {}
            values = [r[f.name] for r in rows if r[f.name] is not None]
            element = f.dataType.elementType if isinstance(f.dataType, T.ArrayType) else None
            nested = isinstance(f.dataType, (T.StructType, T.MapType, T.ArrayType)) and not isinstance(element, T.NumericType)
            if nested and not json_safe(f.dataType):
                raise TypeError(f"column {f.name}: an archive cannot hold the type {f.dataType.simpleString()}")
            if nested:
                chosen, params = "nested", {"raw": True}
            elif chosen in (None, "vector") and isinstance(element, T.NumericType):
                chosen, params = "vector", REGISTRY["vector"].detect(values) | {"type": "float" if isinstance(element, T.FloatType) else "double", "raw": True}
            elif isinstance(f.dataType, T.StringType) and len(set(map(str, values))) > len(values) // 4:
                for name in [chosen] if chosen else REGISTRY:
                    if name not in ("vector", "nested"):
                        found = REGISTRY[name].detect(values)
                        if found is not None:
                            chosen, params = name, found
                            break
            out.append((f.name, f.dataType.simpleString(), chosen, params))
        return cls(out)

    def expand(self, df: DataFrame) -> DataFrame:
        fit, out = [], []
        for i, (name, dtype, codec, params) in enumerate(self.columns):
            c = F.col(quoted(name))
            if codec is None:
                out.append(c)
                continue
            if codec == "nested":
                out.append(F.coalesce(F.to_json(c, JSON), F.lit("null")).alias(f"{name}__raw"))
                continue
            own = REGISTRY[codec](**params)
            parts = own.split(c)
            whole = own.join(parts) if dtype == "string" else own.join(parts).try_cast(dtype)
            same = whole == c
            if dtype in ("array<float>", "array<double>"):
                # Images of numbers have no sign of zero.
                same = same & ~F.exists(c, lambda x: (x == 0) & x.cast("string").startswith("-"))
            fits = F.col(f"_fits_{i}")
            fit.append(F.coalesce(same, F.lit(False)).alias(f"_fits_{i}"))
            out += [F.when(fits, v).alias(f"{name}__{k}") for k, v in parts.items()]
            if dtype == "string":
                out.append(F.when(~fits, c).alias(f"{name}__raw"))
            elif params.get("raw"):
                # JSON; a null array is the text null, so that it is not taken for one that fits.
                out.append(F.when(~fits, F.coalesce(F.to_json(c), F.lit("null"))).alias(f"{name}__raw"))
        return df.select("*", *fit).select(*out)

    @staticmethod
    def parts(name: str, dtype: str, codec: str, params: dict) -> list[str]:
        own = REGISTRY[codec](**params).split(F.lit(None).cast("string") if dtype == "string" else F.col("x"))
        return [*own, *(["raw"] if dtype == "string" or params.get("raw") else [])]

    def needed(self, columns: list[str]) -> list[str]:
        out = []
        for name, dtype, codec, params in self.columns:
            if name in columns:
                out += [name] if codec is None else [f"{name}__{k}" for k in self.parts(name, dtype, codec, params)]
        return out

    def collapse(self, wide: DataFrame, columns: list[str] | None) -> DataFrame:
        out = []
        for name, dtype, codec, params in self.columns:
            if columns is not None and name not in columns:
                continue
            if codec is None:
                out.append(F.col(quoted(name)))
                continue
            raw = F.col(quoted(f"{name}__raw"))
            if codec == "nested":
                out.append(F.when(raw != "null", F.from_json(raw, dtype, JSON)).alias(name))
                continue
            whole = REGISTRY[codec](**params).join({k: F.col(quoted(f"{name}__{k}")) for k in self.parts(name, dtype, codec, params) if k != "raw"})
            if dtype == "string":
                whole = F.coalesce(raw, whole)
            elif params.get("raw"):
                whole = F.when(raw.isNull(), whole.try_cast(dtype)).otherwise(F.from_json(raw, dtype))
            out.append(whole.cast(dtype).alias(name))
        return wide.select(*out)

    def to_json(self) -> str:
        return json.dumps(self.columns)

    @classmethod
    def from_json(cls, text: str) -> Expansion:
        return cls([tuple(c) for c in json.loads(text)])

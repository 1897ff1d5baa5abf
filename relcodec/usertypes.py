"""User types: a decision tree that every value walks down, and a model that hands out walks.

A type is given by two classes. A `Walk` moves many rows at once: which rows are at a leaf, which distribution the
branches of each row have, which branch a value takes, a step down, and the value of a leaf. A `Model` makes walks,
says which aggregate of the table it learns from, learns from its rows, prices itself and writes itself down. The coder
turns the branches of a walk into code bits, so a type needs no arithmetic of its own. Values reach a walk as text.

`TableSpec.with_model(column, ModelClass)` gives a column a type; the class must be importable where executors run.
"""

from __future__ import annotations

import importlib
from abc import ABC, abstractmethod

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relcodec.coder import Decoder, Encoder, Masses, masses_of


class Walk(ABC):
    """The places of many rows in a tree; `live` arguments are the numbers of the rows meant."""

    @abstractmethod
    def at_leaf(self, live: np.ndarray) -> np.ndarray:
        """Whether each row is at a leaf."""

    @abstractmethod
    def branch_masses(self, live: np.ndarray) -> tuple[Masses, np.ndarray]:
        """Distributions over branches, and which of them each row faces."""

    @abstractmethod
    def branch_of(self, values: np.ndarray, live: np.ndarray) -> np.ndarray:
        """The branch that leads to each row's value (`values` holds those of all rows); -1 where none does."""

    @abstractmethod
    def descend(self, live: np.ndarray, branch: np.ndarray) -> None:
        """Take a branch."""

    @abstractmethod
    def leaf_values(self) -> np.ndarray:
        """The value that stands for each row's leaf, as text."""


class Model(ABC):
    """What a type knows of a column."""

    @abstractmethod
    def walk(self, rows: int) -> Walk:
        """A walk of this many rows from the root."""

    @staticmethod
    @abstractmethod
    def statistics(df: DataFrame, value: Column) -> DataFrame:
        """The aggregate to learn from: as small as the model, whatever the table's size."""

    @classmethod
    @abstractmethod
    def finish(cls, rows: list) -> Model:
        """The model that the aggregate's rows make."""

    @abstractmethod
    def cost_bits(self) -> float:
        """Bits that describe the model."""

    @abstractmethod
    def to_record(self) -> dict:
        """The model as plain values for JSON."""

    @classmethod
    @abstractmethod
    def from_record(cls, record: dict) -> Model:
        """The inverse of to_record."""


def name_of(cls: type[Model]) -> str:
    return f"{cls.__module__}:{cls.__qualname__}"


def class_of(name: str) -> type[Model]:
    module, _, cls = name.partition(":")
    return getattr(importlib.import_module(module), cls)


class WalkCoder:
    """Codes a column by walks, in step over the rows that are not at a leaf yet."""

    def __init__(self, model: Model):
        self.model = model

    @classmethod
    def fit(cls, images: DataFrame, column: Column, name: str) -> WalkCoder:
        kind = class_of(name)
        return cls(kind.finish(kind.statistics(images.filter(column.isNotNull()), column).collect()))

    @property
    def bits(self) -> float:
        return self.model.cost_bits()

    def encode(self, enc: Encoder, values: np.ndarray, rows: np.ndarray) -> None:
        own = values[rows]
        walk = self.model.walk(len(rows))
        live = np.flatnonzero(~walk.at_leaf(np.arange(len(rows))))
        while len(live):
            masses, group = walk.branch_masses(live)
            branch = walk.branch_of(own, live)
            entry = masses.find(group, branch)
            if (entry < 0).any():
                raise ValueError(f"{type(self.model).__name__} has no branch for {own[live[int(np.argmin(entry))]]!r}")
            masses.encode(enc, entry, rows[live])
            walk.descend(live, branch)
            live = live[~walk.at_leaf(live)]

    def decode(self, dec: Decoder, rows: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        walk = self.model.walk(len(rows))
        live = np.flatnonzero(~walk.at_leaf(np.arange(len(rows))))
        while len(live):
            masses, group = walk.branch_masses(live)
            branch = masses.symbol[masses.decode(dec, group, rows[live])]
            walk.descend(live, branch)
            live = live[~walk.at_leaf(live)]
        return walk.leaf_values()

    def to_record(self) -> dict:
        return {"model": name_of(type(self.model)), "record": self.model.to_record()}

    @classmethod
    def from_record(cls, record: dict) -> WalkCoder:
        return cls(class_of(record["model"]).from_record(record["record"]))


def distributions(counts: list[list[int]]) -> Masses:
    """Masses of branches 0, 1, ... for several distributions, given their counts."""
    first, symbols, lows, masses = [0], [], [], []
    for row in counts:
        m = masses_of(np.array(row, np.int64))
        first.append(first[-1] + len(m))
        symbols.append(np.arange(len(m))), masses.append(m), lows.append(np.cumsum(m) - m)
    return Masses(np.array(first), np.concatenate(symbols), np.concatenate(lows), np.concatenate(masses))


class StepTree(Model):
    """Whole numbers from 1: at every step the walk stops or goes on, with the same odds."""

    def __init__(self, stops: int, goes: int):
        self.stops, self.goes = stops, goes

    @staticmethod
    def statistics(df, value):
        return df.agg(F.count(F.lit(1)).alias("stops"), F.sum(value.cast("long") - 1).alias("goes"))

    @classmethod
    def finish(cls, rows):
        return cls(int(rows[0]["stops"] or 0), int(rows[0]["goes"] or 0))

    def cost_bits(self):
        return 16.0

    def to_record(self):
        return {"stops": self.stops, "goes": self.goes}

    @classmethod
    def from_record(cls, record):
        return cls(**record)

    def walk(self, rows):
        return StepWalk(distributions([[self.stops, self.goes]]), rows)


class StepWalk(Walk):
    def __init__(self, masses: Masses, rows: int):
        self.masses, self.steps, self.done = masses, np.ones(rows, np.int64), np.zeros(rows, bool)

    def at_leaf(self, live):
        return self.done[live]

    def branch_masses(self, live):
        return self.masses, np.zeros(len(live), np.int64)

    def branch_of(self, values, live):
        aim = np.array([int(values[i]) for i in live], np.int64)
        return np.where(aim < 1, -1, (aim > self.steps[live]).astype(np.int64))

    def descend(self, live, branch):
        self.done[live] = branch == 0
        self.steps[live] += branch

    def leaf_values(self):
        return np.array([*map(str, self.steps.tolist()), None], object)[:-1]


class Sequence(Model):
    """Texts over a small alphabet, such as genomes: each letter or the end, given the letter before; no escape."""

    def __init__(self, alphabet: list[str], counts: list[list[int]]):
        self.alphabet, self.counts = alphabet, counts

    @staticmethod
    def statistics(df, value):
        letters = df.select(F.concat(F.array(F.lit("")), F.filter(F.split(value, ""), lambda x: x != ""), F.array(F.lit(""))).alias("c"))
        pairs = letters.select(F.explode(F.zip_with(F.expr("slice(c, 1, size(c) - 1)"), F.expr("slice(c, 2, size(c) - 1)"), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("p"))
        return pairs.groupBy("p.a", "p.b").agg(F.count(F.lit(1)).alias("n"))

    @classmethod
    def finish(cls, rows):
        alphabet = sorted({r["b"] for r in rows} | {""})
        place = {x: i for i, x in enumerate(alphabet)}
        counts = [[0] * len(alphabet) for _ in alphabet]
        for r in rows:
            counts[place[r["a"]]][place[r["b"]]] = r["n"]
        return cls(alphabet, counts)

    def cost_bits(self):
        return 16.0 * len(self.alphabet) ** 2 + 32.0 * len(self.alphabet)

    def to_record(self):
        return {"alphabet": self.alphabet, "counts": self.counts}

    @classmethod
    def from_record(cls, record):
        return cls(**record)

    def walk(self, rows):
        return SequenceWalk(self, rows)


class SequenceWalk(Walk):
    """Branch 0 is the end: the empty letter sorts first."""

    def __init__(self, model: Sequence, rows: int):
        self.alphabet, self.masses = model.alphabet, distributions(model.counts)
        self.place = {x: i for i, x in enumerate(model.alphabet)}
        self.before, self.done = np.zeros(rows, np.int64), np.zeros(rows, bool)
        self.texts: list[list[str]] = [[] for _ in range(rows)]

    def at_leaf(self, live):
        return self.done[live]

    def branch_masses(self, live):
        return self.masses, self.before[live]

    def branch_of(self, values, live):
        return np.array([self.place.get(values[i][len(self.texts[i]): len(self.texts[i]) + 1], -1) for i in live], np.int64)

    def descend(self, live, branch):
        self.done[live], self.before[live] = branch == 0, branch
        for i, b in zip(live.tolist(), branch.tolist(), strict=True):
            if b:
                self.texts[i].append(self.alphabet[b])

    def leaf_values(self):
        return np.array([*("".join(t) for t in self.texts), None], object)[:-1]

"""Dependency networks: description-length scores, greedy structure search, and fitted models of integer masses.

A node's symbols are a categorical attribute's dictionary places or a number's cells (the top bits of its leaf); the
parents' symbols make its configuration. The objective of a node is the bits that describe its model plus the bits of
its symbols under it, so the search needs contingency counts only.
"""

from __future__ import annotations

import bisect
import itertools
import json
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relcodec.coder import DENSE, MASS, Decoder, Encoder, Masses, RowDecoder, RowEncoder, Sizes, Steps, masses_of, masses_of_groups, put_uniform, take_uniform
from relcodec.schema import Attribute, TableSpec, quoted
from relcodec.usertypes import WalkCoder

CELL_BITS = 10
PARENT_BITS = 5
#: Fewer texts than this go on one by one: a step of arrays costs about as much as that many steps of integers.
ALONE = 48
#: Most contingency cells that the driver takes for one network; beyond it the costliest edges are dropped.
MAX_CELLS = 4_000_000
#: A task hands its counts on once it holds this many.
FLUSH_CELLS = 4_000_000
#: A family's counts of single batches are added up once they are this many.
MERGE_CELLS = 200_000
#: Rows (or bytes) that are counted at once.
COUNTED_ROWS, COUNTED_BYTES = 50_000, 32_000_000
#: Families of at most so many cells are counted in arrays.
ARRAY_CELLS = 1 << 16
#: One cell in so many is drawn to learn how many there are.
DRAWN = 256
#: An attribute and its parents.
Family = tuple[str, tuple[str, ...]]


# ---------------------------------------------------------------- structure

@dataclass(frozen=True)
class Structure:
    """Attributes in coding order with their parents, which come earlier."""

    parents: dict[str, tuple[str, ...]]

    @classmethod
    def empty(cls, names: list[str]) -> Structure:
        return cls({n: () for n in names})

    @classmethod
    def from_edges(cls, names: list[str], edges: list[tuple[str, str]]) -> Structure:
        """A network given by hand; a cycle is an error."""
        wanted = {n: [p for p, c in edges if c == n] for n in names}
        order: dict[str, tuple[str, ...]] = {}
        while len(order) < len(names):
            ready = [n for n in names if n not in order and all(p in order for p in wanted[n])]
            if not ready:
                raise ValueError(f"these attributes depend on each other in a cycle: {sorted(set(names) - set(order))}")
            order[ready[0]] = tuple(wanted[ready[0]])
        return cls(order)

    @classmethod
    def random(cls, names: list[str], seed: int, max_parents: int = 2) -> Structure:
        """Random parents in a random order: the control of a bad network."""
        rng = np.random.default_rng(seed)
        order = [names[i] for i in rng.permutation(len(names))]
        return cls({n: tuple(sorted(order[j] for j in rng.choice(i, min(i, int(rng.integers(0, max_parents + 1))), replace=False))) if i else () for i, n in enumerate(order)})

    @property
    def coding_order(self) -> list[str]:
        return list(self.parents)

    @property
    def edges(self) -> list[tuple[str, str]]:
        return [(p, c) for c, ps in self.parents.items() for p in ps]

    def without(self, child: str, parent: str) -> Structure:
        return Structure({c: tuple(p for p in ps if (c, p) != (child, parent)) for c, ps in self.parents.items()})

    def depends_on(self, name: str) -> set[str]:
        """All that an attribute depends on, whatever the order of `parents`."""
        seen: set[str] = set()
        todo = list(self.parents[name])
        while todo:
            n = todo.pop()
            if n not in seen:
                seen.add(n)
                todo += self.parents[n]
        return seen

    def ancestors(self, names: list[str]) -> list[str]:
        """The named attributes and all they depend on, in coding order."""
        need, todo = set(), list(names)
        while todo:
            n = todo.pop()
            if n not in need:
                need.add(n)
                todo += self.parents[n]
        return [n for n in self.parents if n in need]


# ---------------------------------------------------------------- scores

def model_bits(cells: int, configs: int, domain: int, accounting: str = "sparse") -> float:
    """Bits that describe a node: only the entries that occur, or a full table of 32- or 8-bit numbers."""
    if accounting == "sparse":
        return cells * (math.ceil(math.log2(max(domain, 2))) + 16) + 16 * configs
    return configs * max(domain - 1, 0) * (32 if accounting == "dense" else 8)


def score_local(child: np.ndarray, config: np.ndarray, domain: int, score: str = "mdl", scale: float = 1.0, accounting: str = "sparse") -> float:
    """Objective of one node on sample rows. score: mdl, mdl_scaled (data part grown to `scale` rows per sample row, by
    adaptive code lengths that punish configurations seen once), bic, nll."""
    pair, n_pair = np.unique(config * np.int64(domain) + child, return_counts=True)
    _, n_config = np.unique(pair // domain, return_inverse=True)
    total = np.bincount(n_config, n_pair)
    nll = float((total * np.log2(total)).sum() - (n_pair * np.log2(n_pair)).sum())
    if score == "nll":
        return nll
    if score == "bic":
        return nll + 0.5 * len(total) * (domain - 1) * math.log2(max(len(child), 2))
    bits = model_bits(len(pair), len(total), domain, accounting)
    if score == "mdl":
        return bits + nll
    # Prequential, add-half: log2 Gamma(n + K/2) / Gamma(K/2) - sum log2 Gamma(c + 1/2) / Gamma(1/2).
    def lg(counts: np.ndarray, more: float) -> float:
        # Few counts are distinct.
        some, times = np.unique(counts, return_counts=True)
        return sum(int(t) * (math.lgamma(c + more) - math.lgamma(more)) for c, t in zip(some.tolist(), times.tolist(), strict=True))

    adaptive = (lg(total, domain / 2) - lg(n_pair, 0.5)) / math.log(2)
    return bits + scale * adaptive


def learn_structure(symbols: dict[str, np.ndarray], domains: dict[str, int], max_parents: int | None = 4, score: str = "mdl", scale: float = 1.0,
                    accounting: str = "sparse", lookahead: int = 1, score_set: Callable | None = None) -> Structure:
    """Greedy search for an order and parents.

    Every attribute that has no place yet grows a parent set from the placed ones while its objective falls; the one
    with the lowest objective is placed next (ties by schema order). An objective depends only on (parent set, child),
    so each is computed once and remembered over all rounds.
    """
    names = list(symbols)
    memo: dict[tuple[frozenset, str], float] = {}

    def objective(parents: frozenset, child: str) -> float:
        if (parents, child) not in memo:
            if score_set:
                memo[parents, child] = score_set(parents, child)
            else:
                config = np.zeros(len(symbols[child]), np.int64)
                for p in sorted(parents):
                    config = np.unique(config * np.int64(domains[p]) + symbols[p], return_inverse=True)[1]
                memo[parents, child] = score_local(symbols[child], config, domains[child], score, scale, accounting)
        return memo[parents, child]

    placed: dict[str, tuple[str, ...]] = {}
    best: dict[str, tuple[float, frozenset]] = {n: (objective(frozenset(), n), frozenset()) for n in names}
    while len(placed) < len(names):
        for child in (n for n in names if n not in placed):
            now, parents = objective(frozenset(), child), frozenset()
            while max_parents is None or len(parents) < max_parents:
                more = [p for p in placed if p not in parents]
                options = [parents | {p} for p in more]
                found = min(((objective(o, child), i) for i, o in enumerate(options)), default=(math.inf, 0))
                if found[0] >= now and lookahead > 1 and (max_parents is None or len(parents) + 2 <= max_parents):
                    options = [parents | set(two) for two in itertools.combinations(more, 2)]
                    found = min(((objective(o, child), i) for i, o in enumerate(options)), default=(math.inf, 0))
                if found[0] >= now:
                    break
                now, parents = found[0], options[found[1]]
            best[child] = (now, parents)
        child = min((n for n in names if n not in placed), key=lambda n: (best[n][0], names.index(n)))
        placed[child] = tuple(sorted(best[child][1], key=names.index))
    return Structure(placed)


def brute_force_structure(symbols: dict[str, np.ndarray], domains: dict[str, int], accounting: str = "sparse") -> tuple[float, Structure]:
    """The best network over all orders (at most 5 attributes), to judge the greedy search by."""
    names = list(symbols)
    assert len(names) <= 5
    memo: dict = {}

    def objective(parents: frozenset, child: str) -> float:
        if (parents, child) not in memo:
            config = np.zeros(len(symbols[child]), np.int64)
            for p in sorted(parents):
                config = np.unique(config * np.int64(domains[p]) + symbols[p], return_inverse=True)[1]
            memo[parents, child] = score_local(symbols[child], config, domains[child], accounting=accounting)
        return memo[parents, child]

    best = (math.inf, Structure.empty(names))
    for order in itertools.permutations(names):
        total, chosen = 0.0, {}
        for i, child in enumerate(order):
            sets = [frozenset(s) for k in range(i + 1) for s in itertools.combinations(order[:i], k)]
            p = min(sets, key=lambda s: objective(s, child))
            total += objective(p, child)
            chosen[child] = tuple(sorted(p, key=names.index))
        if total < best[0]:
            best = (total, Structure(chosen))
    return best


# ---------------------------------------------------------------- symbols

def symbol_column(a: Attribute, as_parent: bool = False) -> Column:
    """The node symbol of an attribute's image, as a string for grouping: its value, cell or (as a parent) bucket."""
    c = F.col(quoted(a.name))
    if a.kind == "string":
        # A text's view as a predictor is the bit length of its length.
        return F.when(c.isNull(), None).otherwise(F.length(F.bin(F.length(c).cast("long"))).cast("string"))
    if a.kind == "user":
        return c.isNotNull().cast("int").cast("string")
    if not a.numeric:
        return c
    return F.shiftright(a.leaf(c), max(0, a.depth - (PARENT_BITS if as_parent else CELL_BITS))).cast("string")


def image_values(column: pa.ChunkedArray | pa.Array, a: Attribute) -> np.ndarray | pa.Array:
    """An image column in the coder's form: categorical values stay in Arrow, numbers are leaf numbers (objects where some
    are NULL), texts objects."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if a.kind == "categorical":
        return column
    if not a.numeric:
        return np.array(column.to_pylist() + [None], object)[:-1]
    some = column.is_valid().to_numpy(zero_copy_only=False)
    whole = pc.fill_null(column, 0).to_numpy(zero_copy_only=False)
    whole = a.leaves_of(whole) if a.bitwise else whole.astype(np.int64)
    if some.all():
        return whole
    out = whole.astype(object)
    out[~some] = None
    return out


def symbols_of(values: np.ndarray | pa.Array, a: Attribute, as_parent: bool = False) -> np.ndarray:
    """Symbol numbers of image values in the coder; -1 for a value outside the domain."""
    if a.kind == "categorical":
        column = values if isinstance(values, pa.Array) else pa.array(values.tolist(), pa.string())
        return pc.fill_null(pc.index_in(column, pa.array(a.dictionary, pa.string())), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    null = np.array([v is None for v in values], bool) if values.dtype == object else np.zeros(len(values), bool)
    if a.kind == "user":
        return (~null).astype(np.int64)
    if a.kind == "string":
        return np.fromiter((-1 if v is None else len(v).bit_length() or 1 for v in values), np.int64, len(values)) + 1
    whole = np.array([0 if v is None else v for v in values], np.int64) if values.dtype == object else values.astype(np.int64)
    symbol = np.where(null, 0, (whole >> max(0, a.depth - (PARENT_BITS if as_parent else CELL_BITS))) + 1)
    return np.where(~null & ((whole < 0) | (whole >= a.leaves)), -1, symbol)


def domain_of(a: Attribute, as_parent: bool = False) -> int:
    if a.kind == "categorical":
        return max(1, len(a.dictionary))
    if a.kind in ("string", "user"):
        return 64 if a.kind == "string" else 2
    return (1 << min(a.depth, PARENT_BITS if as_parent else CELL_BITS)) + 1


def contingency(images: DataFrame, spec: TableSpec, structure: Structure) -> DataFrame:
    """node, config (symbols of the parents), value, cnt for all nodes in one scan and one shuffle of partial counts."""
    rows = F.array(*[F.struct(F.lit(n).alias("node"), F.array(*[symbol_column(spec[p], True) for p in ps]).cast("array<string>").alias("config"), symbol_column(spec[n]).alias("value"))
                     for n, ps in structure.parents.items()])
    one = images.select(F.explode(rows).alias("r"))
    return one.groupBy("r.node", "r.config", "r.value").agg(F.count(F.lit(1)).alias("cnt"))


# ---------------------------------------------------------------- fitted nodes

def config_keys(parents: tuple[Attribute, ...], known: dict[str, np.ndarray], rows: int) -> np.ndarray:
    """One number per configuration of parent symbols; -1 where a parent is outside its domain."""
    key, bad = np.zeros(rows, np.int64), np.zeros(rows, bool)
    for p in parents:
        bad |= known[p.name] < 0
        key = key * domain_of(p, True) + np.maximum(known[p.name], 0)
    return np.where(bad, -1, key)


def most_cells(spec: TableSpec, family: Family) -> int:
    """Cells that a family (child, parents) has at most, one more a parent and two more of the child for strange values."""
    child, parents = family
    return (math.prod(domain_of(spec[p], True) for p in parents) + 1) * (domain_of(spec[child]) + 2)


def summed(codes: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes in order, and how often each occurs."""
    if counts is None:
        codes = np.sort(codes)
    else:
        by = np.argsort(codes, kind="stable")
        codes, counts = codes[by], counts[by]
    new = np.ones(len(codes), bool)
    new[1:] = codes[1:] != codes[:-1]
    starts = np.flatnonzero(new)
    return codes[starts], np.diff(np.append(starts, len(codes))) if counts is None else np.add.reduceat(counts, starts) if len(codes) else counts


def drawn_cells(codes: np.ndarray) -> np.ndarray:
    """Whether a cell is one of the share of 1 / DRAWN that its hash draws."""
    h = codes.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return (h ^ (h >> np.uint64(32))) % np.uint64(DRAWN) == 0


def joined(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    """The same rows in tables of at least so many, but for the last."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) >= rows or sum(b.nbytes for b in held) >= COUNTED_BYTES:
            yield pa.Table.from_batches(held)
            held = []
    if held:
        yield pa.Table.from_batches(held)


def cells(images: DataFrame, spec: TableSpec, families: list[Family], drawn: frozenset[int] = frozenset()) -> DataFrame:
    """node (place among the families (child, parents)), key, symbol, cnt: partial counts per task, added up in one shuffle.

    Of families in `drawn` only the cells that their hash draws, one in DRAWN, which tell about how many there are."""
    schema = pa.schema([("node", pa.int32()), ("key", pa.int64()), ("symbol", pa.int64()), ("cnt", pa.int64())])
    plan = [(spec[n], tuple(spec[p] for p in ps)) for n, ps in families]
    needed = {p.name for _, ps in plan for p in ps}
    names = {a.name for a, _ in plan}
    most = [most_cells(spec, f) for f in families]

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # A code is a configuration and a symbol, both from 0 on; few codes are counted in an array by code.
        arrays = {i: np.zeros(m, np.int64) for i, m in enumerate(most) if m <= ARRAY_CELLS and i not in drawn}
        held: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in plan]
        sizes = np.zeros(len(plan), np.int64)

        def given(i: int, codes: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
            key, s = np.divmod(codes, domain_of(plan[i][0]) + 2)
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(codes), i, np.int32)), pa.array(key - 1), pa.array(s - 1), pa.array(n.astype(np.int64))], schema=schema)

        def merge(i: int) -> None:
            held[i] = [summed(*(np.concatenate([p[k] for p in held[i]]) for k in range(2)))]
            sizes[i] = len(held[i][0][0])

        for batch in joined(batches, COUNTED_ROWS):
            values = {n: image_values(batch.column(n), spec[n]) for n in names | needed}
            own = {n: symbols_of(values[n], spec[n]) for n in names}
            known = {n: own[n] if n in own and spec[n].kind == "categorical" else symbols_of(values[n], spec[n], True) for n in needed}
            keys: dict[tuple, np.ndarray] = {}
            for i, (a, ps) in enumerate(plan):
                if families[i][1] not in keys:
                    keys[families[i][1]] = config_keys(ps, known, batch.num_rows) + 1
                if most[i] >= 1 << 62 and i not in drawn:
                    # No number tells such a cell: its two are handed on as they are.
                    pair, n = np.unique(np.stack([keys[families[i][1]] - 1, own[a.name]]), axis=1, return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), i, np.int32)), pa.array(pair[0]), pa.array(pair[1]), pa.array(n.astype(np.int64))], schema=schema)
                    continue
                codes = keys[families[i][1]] * (domain_of(a) + 2) + (own[a.name] + 1)
                if i in arrays:
                    arrays[i] += np.bincount(codes, minlength=most[i])
                    continue
                held[i].append(summed(codes[drawn_cells(codes)] if i in drawn else codes))
                sizes[i] += len(held[i][-1][0])
                if sizes[i] > 2 * max(MERGE_CELLS, len(held[i][0][0])):
                    merge(i)
            while sizes.sum() > FLUSH_CELLS:
                i = int(sizes.argmax())
                merge(i)
                yield given(i, *held[i][0])
                held[i], sizes[i] = [], 0
        for i, counts in arrays.items():
            codes = np.flatnonzero(counts)
            if len(codes):
                yield given(i, codes, counts[codes])
        for i in range(len(plan)):
            if held[i]:
                merge(i)
                yield given(i, *held[i][0])

    return images.mapInArrow(counted, "node int, key long, symbol long, cnt long").groupBy("node", "key", "symbol").agg(F.sum("cnt").alias("cnt"))


def family_bits(images: DataFrame, spec: TableSpec, families: list[tuple[str, tuple[str, ...]]], with_model: bool = True) -> list[float]:
    """Objective of each family on all rows, as it would be coded (or its data bits alone): one scan for all of them."""
    return bits_of_counts(cells(images, spec, families), spec, families, with_model)


def bits_of_counts(counts: DataFrame, spec: TableSpec, families: list[Family], with_model: bool = True) -> list[float]:
    """Objectives of families by their `cells`."""
    n = F.col("cnt").cast("double")
    per = counts.groupBy("node", "key").agg(F.count(F.lit(1)).alias("cells"), F.sum(n).alias("g"), F.sum(n * F.log2(n)).alias("s"))
    rows = per.groupBy("node").agg(F.sum("cells").alias("cells"), F.count(F.lit(1)).alias("configs"), F.sum(F.col("g") * F.log2("g") - F.col("s")).alias("data")).collect()
    price = lambda r: model_bits(r["cells"], r["configs"], domain_of(spec[families[r["node"]][0]])) if with_model else 0.0
    found = {r["node"]: price(r) + r["data"] for r in rows}
    return [found.get(i, 0.0) for i in range(len(families))]


def near_functions(symbols: dict[str, np.ndarray], domains: dict[str, int], most: int = 3) -> list[tuple[str, str]]:
    """(parent, child) pairs of a sample in which the parent's repeated values (nearly) always have one value of the
    child: what a small sample shows of a key and its attributes, though most values of the key occur once in it."""
    out = []
    for child, c in symbols.items():
        if len(np.unique(c)) < 2:
            continue
        _, often = np.unique(c, return_counts=True)
        found = []
        for parent, p in symbols.items():
            if parent == child:
                continue
            order = np.lexsort((c, p))
            same = np.flatnonzero(p[order][1:] == p[order][:-1])
            # By chance neighbours would agree as often as two rows do anywhere.
            chance = float(((often / len(c)) ** 2).sum())
            agree = float((c[order][same] == c[order][same + 1]).mean()) if len(same) >= 20 else 0.0
            if agree > 0.9 and agree > chance + 0.05:
                found.append((domains[parent], parent))
        out += [(parent, child) for _, parent in sorted(found)[:most]]
    return out


def with_key_parents(images: DataFrame, spec: TableSpec, structure: Structure, symbols: dict[str, np.ndarray], domains: dict[str, int]) -> Structure:
    """Keys before what they nearly determine, where that is shorter on all rows than the families found.

    A key becomes the only parent of the attributes that gain by it: of those it does not depend on itself, or, as a
    root, of all (then its children depend on nothing else and it on nothing, so there is no cycle). The change that
    gains most goes first."""
    pairs = [(p, c) for p, c in near_functions(symbols, domains) if spec[c].kind not in ("string", "user")]
    if not pairs:
        return structure
    families = key_families(structure, pairs)
    return with_pairs(spec, structure, pairs, dict(zip(families, family_bits(images, spec, families), strict=True)))


def key_families(structure: Structure, pairs: list[tuple[str, str]]) -> list[Family]:
    """Families whose objectives `with_pairs` compares."""
    names, keys = sorted({x for pair in pairs for x in pair}), sorted({p for p, _ in pairs})
    return list(dict.fromkeys([(n, structure.parents[n]) for n in names] + [(k, ()) for k in keys] + [(c, (p,)) for p, c in pairs]))


def with_pairs(spec: TableSpec, structure: Structure, pairs: list[tuple[str, str]], price: dict[Family, float]) -> Structure:
    """`with_key_parents` for (key, child) pairs and the objectives of their families."""
    keys = sorted({p for p, _ in pairs})
    now = {n: price[n, structure.parents[n]] for n in sorted({x for pair in pairs for x in pair})}
    chosen = dict(structure.parents)
    while True:
        best = (0.0, "", [], False)
        for k in keys:
            children = [c for p, c in pairs if p == k and price[c, (k,)] < now[c]]
            above = Structure(chosen).depends_on(k)
            free = [c for c in children if c not in above]
            for root, some in ((False, free), (True, children)):
                gain = (now[k] - price[k, ()] if root else 0.0) + sum(now[c] - price[c, (k,)] for c in some)
                if some and gain > best[0] + 1e-6:
                    best = (gain, k, some, root)
        _, key, children, root = best
        if not children:
            break
        if root:
            chosen[key], now[key] = (), price[key, ()]
        for c in children:
            chosen[c], now[c] = (key,), price[c, (key,)]
    return Structure.from_edges(spec.names, [(p, c) for c, ps in chosen.items() for p in ps])


@dataclass
class Node:
    """One attribute's model: masses per configuration (configuration 0 is the marginal, for configurations never seen).

    Every distribution keeps one unit of mass for `escape`, a symbol it has not seen; an escaped symbol is coded by the
    marginal, and there as a plain number. Numbers go on with the bits below their cell, all equally likely; texts with
    their length and characters.
    """

    attribute: Attribute
    parents: tuple[Attribute, ...]
    configs: np.ndarray
    masses: Masses
    chars: CharModel | WalkCoder | None = None
    bits: float = 0.0
    escape: int = field(default=0)
    places: np.ndarray | None = field(default=None, repr=False, compare=False)  # groups by configuration, where those are few

    @classmethod
    def fit(cls, a: Attribute, parents: tuple[Attribute, ...], keys: np.ndarray, symbols: np.ndarray, counts: np.ndarray, escape: bool = True) -> Node:
        """keys, symbols, counts: how often a symbol occurred in a configuration of the parents (`config_keys`)."""
        size = domain_of(a)
        seen, at = np.unique(symbols, return_inverse=True)
        n = np.bincount(at, counts, len(seen)).astype(np.int64)
        seen, n = (np.append(seen, size), np.append(n, 0)) if escape or not len(seen) else (seen, n)
        mass = masses_of(n)
        configs, table = np.zeros(1, np.int64), Masses(np.array([0, len(seen)]), seen, np.cumsum(mass) - mass, mass)
        if parents and (keys >= 0).any():
            order = np.lexsort((symbols, keys))
            order = order[keys[order] >= 0]
            keys, symbols, counts = keys[order], symbols[order], counts[order]
            starts = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
            sizes = np.diff(np.append(starts, len(keys))) + int(escape)
            first = np.append(0, np.cumsum(sizes))
            # The escape is the last entry of its configuration.
            entries, n = np.full(first[-1], size, np.int64), np.zeros(first[-1], np.int64)
            at = np.arange(len(keys)) + np.repeat(np.arange(len(starts)), sizes - int(escape)) * int(escape)
            entries[at], n[at] = symbols, counts
            own, mass = masses_of_groups(n, first)
            low = np.cumsum(mass) - mass - MASS * own
            configs = np.append(configs, keys[starts] + 1)
            table = Masses(np.append(0, table.first[-1] + first), np.append(table.symbol, entries), np.append(table.low, low), np.append(table.mass, mass))
        out = cls(a, parents, configs, table, escape=size)
        out.bits = model_bits(len(out.masses.symbol), len(out.configs), size)
        return out

    def group(self, known: dict[str, np.ndarray], rows: int) -> np.ndarray:
        if not self.parents:
            return np.zeros(rows, np.int64)
        key = config_keys(self.parents, known, rows)
        if self.places is None and (size := math.prod(domain_of(p, True) for p in self.parents) + 1) <= DENSE:
            self.places = np.zeros(size, np.int32)
            self.places[self.configs] = np.arange(len(self.configs))
        if self.places is not None:
            return self.places[key + 1].astype(np.int64)
        bad = key < 0
        at = np.minimum(np.searchsorted(self.configs, key + 1), len(self.configs) - 1)
        return np.where((self.configs[at] == key + 1) & ~bad, at, 0)

    def encode(self, enc: Encoder, values: np.ndarray, known: dict[str, np.ndarray], s: np.ndarray) -> None:
        """Code values with symbols s."""
        n = len(values)
        if (s < 0).any():
            bad = values[int(np.flatnonzero(s < 0)[0])]
            raise ValueError(f"{self.attribute.name}: {bad!r} is not in the attribute's domain")
        group = self.group(known, n)
        entry = self.masses.find(group, s)
        for _ in range(2):
            lost = np.flatnonzero(entry < 0)
            if not len(lost):
                break
            out = self.masses.find(group[lost], np.full(len(lost), self.escape))
            self.masses.encode(enc, out, lost)
            plain = lost[group[lost] == 0]
            put_uniform(enc, s[plain], max(1, self.escape.bit_length()), plain)
            again = lost[group[lost] != 0]
            group[again] = 0
            entry[plain] = np.iinfo(np.int64).max
            entry[again] = self.masses.find(group[again], s[again])
            # Those that escaped are done or coded below by the marginal.
        rest = np.flatnonzero((entry >= 0) & (entry != np.iinfo(np.int64).max))
        self.masses.encode(enc, entry[rest], rest)
        if self.attribute.numeric:
            some = np.flatnonzero(s > 0)
            low = max(0, self.attribute.depth - CELL_BITS)
            if low:
                v = values[some].astype(np.int64)
                put_uniform(enc, v & ((1 << low) - 1), low, some)
        elif self.attribute.kind in ("string", "user"):
            self.chars.encode(enc, values, np.flatnonzero(s > 0))

    def decode(self, dec: Decoder, known: dict[str, np.ndarray]) -> np.ndarray:
        n = len(dec.at)
        rows = np.arange(n)
        group = self.group(known, n)
        s = self.masses.symbol[self.masses.decode(dec, group, rows)]
        lost = np.flatnonzero(s == self.escape)
        if len(lost):
            again = lost[group[lost] != 0]
            s[again] = self.masses.symbol[self.masses.decode(dec, np.zeros(len(again), np.int64), again)]
            plain = np.concatenate([lost[group[lost] == 0], again[s[again] == self.escape]])
            s[plain] = take_uniform(dec, max(1, self.escape.bit_length()), plain)
        a = self.attribute
        if a.kind == "categorical":
            return np.array([*a.dictionary, None], object)[s]
        out = np.full(n, None, object)
        some = np.flatnonzero(s > 0)
        if a.numeric:
            low = max(0, a.depth - CELL_BITS)
            v = (s[some] - 1) << low
            if low:
                v |= take_uniform(dec, low, some)
            out[some] = v
        else:
            out[some] = self.chars.decode(dec, some, s[some])
        return out

    def to_record(self, numbers: Callable = np.ndarray.tolist) -> dict:
        m = self.masses
        return {"name": self.attribute.name, "parents": [p.name for p in self.parents], "configs": numbers(self.configs), "first": numbers(m.first), "symbol": numbers(m.symbol), "mass": numbers(m.mass), "escape": self.escape, "bits": self.bits,
                "chars": self.chars.to_record() if self.chars else None}

    @classmethod
    def from_record(cls, r: dict, spec: TableSpec) -> Node:
        first, mass = np.array(r["first"]), np.array(r["mass"], np.int64)
        total = np.cumsum(mass) - mass
        low = total - np.repeat(total[first[:-1]], np.diff(first))
        chars = (WalkCoder if "model" in r["chars"] else CharModel).from_record(r["chars"]) if r["chars"] else None
        return cls(spec[r["name"]], tuple(spec[p] for p in r["parents"]), np.array(r["configs"], np.int64), Masses(first, np.array(r["symbol"], np.int64), low, mass), chars, r["bits"], r["escape"])


class CharModel:
    """Characters by their `order` predecessors (each hashed by code point; 0 before the start), with an escape to code points."""

    def __init__(self, order: int, contexts: np.ndarray, masses: Masses):
        self.order, self.contexts, self.masses = order, contexts, masses
        self.escape = 0x110000
        self.places = {c: i for i, c in enumerate(contexts.tolist())}
        self.made: dict = {}

    @classmethod
    def fit(cls, order: int, cells: list[tuple[int, int, int]]) -> CharModel:
        """cells: (context, code point, count); contexts seen, and 0x7fff... for all, whose row is the fallback."""
        table: dict[int, dict[int, int]] = {-1: {}}
        for context, char, n in cells:
            table.setdefault(context, {})[char] = table.get(context, {}).get(char, 0) + n
            table[-1][char] = table[-1].get(char, 0) + n
        first, symbols, lows, masses = [0], [], [], []
        contexts = np.array(sorted(table), np.int64)
        for k in contexts.tolist():
            row = sorted(table[k].items())[:30000]
            s = np.array([x for x, _ in row] + [0x110000], np.int64)
            m = masses_of(np.array([x for _, x in row] + [0], np.int64))
            first.append(first[-1] + len(s))
            symbols.append(s), masses.append(m), lows.append(np.cumsum(m) - m)
        return cls(order, contexts, Masses(np.array(first), np.concatenate(symbols), np.concatenate(lows), np.concatenate(masses)))

    def group(self, context: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.contexts, context), len(self.contexts) - 1)
        return np.where(self.contexts[at] == context, at, 0)

    def next(self, context: np.ndarray, char: np.ndarray) -> np.ndarray:
        return char if self.order == 1 else (context % (1 << 21)) << 21 | char if self.order == 2 else np.zeros_like(char)

    def next_one(self, context: int, char: int) -> int:
        return char if self.order == 1 else (context % (1 << 21)) << 21 | char if self.order == 2 else 0

    def tables(self, context: int) -> tuple[int, dict[int, tuple[int, int]], list[int], list[int]]:
        """A context's group with its masses by symbol, its lows and its symbols, kept once made."""
        group = self.places.get(context, 0)
        if group not in self.made:
            a, b = int(self.masses.first[group]), int(self.masses.first[group + 1])
            symbol, low, mass = (x[a:b].tolist() for x in (self.masses.symbol, self.masses.low, self.masses.mass))
            self.made[group] = (group, {s: (c, c + m) for s, c, m in zip(symbol, low, mass, strict=True)}, low, symbol)
        return self.made[group]

    def encode_one(self, enc: RowEncoder, chars: list[int], context: int) -> None:
        for char in chars:
            group, table, _, _ = self.tables(context)
            if char not in table and group:
                enc.put(*table[self.escape])
                group, table = 0, self.tables(-1)[1]
            if char in table:
                enc.put(*table[char])
            else:
                enc.put(*table[self.escape])
                enc.put_uniform(char, 21)
            context = self.next_one(context, char)
        enc.close()

    def decode_one(self, dec: RowDecoder, count: int, context: int) -> list[int]:
        def symbol(table: dict, lows: list[int], symbols: list[int]) -> int:
            at = bisect.bisect_right(lows, dec.position()) - 1
            for _ in range(2):
                at = min(max(at + dec.holds(*table[symbols[at]]), 0), len(symbols) - 1)
            dec.take(*table[symbols[at]])
            return symbols[at]

        out = []
        for _ in range(count):
            group, *own = self.tables(context)
            char = symbol(*own)
            if char == self.escape and group:
                char = symbol(*self.tables(-1)[1:])
            if char == self.escape:
                char = dec.take_uniform(21)
            out.append(char)
            context = self.next_one(context, char)
        dec.close()
        return out

    def encode(self, enc: Encoder, values: np.ndarray, rows: np.ndarray) -> None:
        texts = [np.frombuffer(values[i].encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64) for i in rows]
        size = np.array([len(t) for t in texts], np.int64)
        # The node's symbol is the bit length of the length; its lower bits follow.
        bits = np.maximum(1, np.frexp(size.astype(float))[1])
        put_uniform(enc, size & ((np.int64(1) << (bits - 1)) - 1) if len(size) else size, np.maximum(bits - 1, 0), rows)
        put_uniform(enc, (size > 0).astype(np.int64), (bits == 1).astype(np.int64), rows)
        flat = np.concatenate([*texts, np.zeros(1, np.int64)])
        start = np.cumsum(size) - size
        context = np.zeros(len(rows), np.int64)
        for k in range(int(size.max()) if len(size) else 0):
            live = np.flatnonzero(size > k)
            if len(live) < ALONE:
                for i in live.tolist():
                    self.encode_one(RowEncoder(enc, int(rows[i])), flat[start[i] + k: start[i] + size[i]].tolist(), int(context[i]))
                break
            char = flat[start[live] + k]
            group = self.group(context[live])
            entry = self.masses.find(group, char)
            for _ in range(2):
                lost = np.flatnonzero(entry < 0)
                if not len(lost):
                    break
                self.masses.encode(enc, self.masses.find(group[lost], np.full(len(lost), self.escape)), rows[live[lost]])
                plain, again = lost[group[lost] == 0], lost[group[lost] != 0]
                put_uniform(enc, char[plain], 21, rows[live[plain]])
                entry[plain] = np.iinfo(np.int64).max
                group[again] = 0
                entry[again] = self.masses.find(group[again], char[again])
            rest = np.flatnonzero((entry >= 0) & (entry != np.iinfo(np.int64).max))
            self.masses.encode(enc, entry[rest], rows[live[rest]])
            context[live] = self.next(context[live], char)

    def decode(self, dec: Decoder, rows: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        bits = symbol - 1
        size = np.where(bits > 1, np.int64(1) << np.maximum(bits - 1, 0), 0)
        size |= take_uniform(dec, np.maximum(bits - 1, 0), rows)
        size |= take_uniform(dec, (bits == 1).astype(np.int64), rows)
        start = np.cumsum(size) - size
        flat = np.zeros(int(size.sum()), np.int64)
        context = np.zeros(len(rows), np.int64)
        for k in range(int(size.max()) if len(size) else 0):
            live = np.flatnonzero(size > k)
            if len(live) < ALONE:
                for i in live.tolist():
                    flat[start[i] + k: start[i] + size[i]] = self.decode_one(RowDecoder(dec, int(rows[i])), int(size[i]) - k, int(context[i]))
                break
            group = self.group(context[live])
            char = self.masses.symbol[self.masses.decode(dec, group, rows[live])]
            lost = np.flatnonzero(char == self.escape)
            if len(lost):
                again = lost[group[lost] != 0]
                char[again] = self.masses.symbol[self.masses.decode(dec, np.zeros(len(again), np.int64), rows[live[again]])]
                plain = np.concatenate([lost[group[lost] == 0], again[char[again] == self.escape]])
                char[plain] = take_uniform(dec, 21, rows[live[plain]])
            flat[start[live] + k] = char
            context[live] = self.next(context[live], char)
        data = flat.astype("<u4")
        return np.array([data[a: a + n].tobytes().decode("utf-32-le", "surrogatepass") for a, n in zip(start, size, strict=True)] + [None], object)[:-1]

    def to_record(self) -> dict:
        m = self.masses
        return {"order": self.order, "contexts": self.contexts.tolist(), "first": m.first.tolist(), "symbol": m.symbol.tolist(), "mass": m.mass.tolist()}

    @classmethod
    def from_record(cls, r: dict) -> CharModel:
        first, mass = np.array(r["first"]), np.array(r["mass"], np.int64)
        total = np.cumsum(mass) - mass
        return cls(r["order"], np.array(r["contexts"], np.int64), Masses(first, np.array(r["symbol"], np.int64), total - np.repeat(total[first[:-1]], np.diff(first)), mass))


@dataclass
class Network:
    """Fitted nodes in coding order: all that a decoder needs besides the codes."""

    spec: TableSpec
    nodes: list[Node]

    @property
    def structure(self) -> Structure:
        return Structure({n.attribute.name: tuple(p.name for p in n.parents) for n in self.nodes})

    @property
    def bits(self) -> float:
        return sum(n.bits for n in self.nodes)

    def encoder(self, columns: dict[str, np.ndarray], rows: int) -> Encoder:
        """An encoder that took all values of image columns."""
        enc, known = Encoder(rows), {}
        for node in self.nodes:
            a, values = node.attribute, columns[node.attribute.name]
            own = symbols_of(values, a)
            node.encode(enc, values, known, own)
            known[a.name] = own if a.kind == "categorical" else symbols_of(values, a, True)
        return enc

    def encode(self, columns: dict[str, np.ndarray], rows: int) -> tuple[np.ndarray, np.ndarray]:
        """(bits end to end, bits per row) of image columns."""
        return self.encoder(columns, rows).codes()

    def decode(self, payload: bytes, starts: np.ndarray, last: int | None = None) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """(image columns of the first `last` nodes, where each code ends if all were decoded)."""
        dec, known, out = Decoder(payload, starts), {}, {}
        for node in self.nodes[:last]:
            values = node.decode(dec, known)
            known[node.attribute.name] = symbols_of(values, node.attribute, True)
            out[node.attribute.name] = values
        return out, dec.ends()

    def to_json(self) -> str:
        return json.dumps({"spec": self.spec.to_json(), "nodes": [n.to_record() for n in self.nodes]})

    @classmethod
    def from_json(cls, text: str) -> Network:
        raw = json.loads(text)
        spec = TableSpec.from_json(raw["spec"])
        return cls(spec, [Node.from_record(r, spec) for r in raw["nodes"]])


def code_sizes(networks: list[list[Node]], columns: dict[str, np.ndarray], rows: int) -> list[np.ndarray]:
    """Bits of every row's code by the nodes of each network (all over the same attributes), as their encoders have them.

    The steps of a node that several networks have are found once, and as far as networks begin with the same nodes they
    are coded as one."""
    own: dict[str, np.ndarray] = {}
    known: dict[str, np.ndarray] = {}
    steps: dict[int, list] = {}

    def take(node: Node, enc: Sizes) -> None:
        a, values = node.attribute, columns[node.attribute.name]
        for x in (a, *(p for p in node.parents if p.kind == "categorical")):
            if x.name not in own:
                own[x.name] = symbols_of(columns[x.name], x)
        for p in node.parents:
            if p.name not in known:
                known[p.name] = own[p.name] if p.kind == "categorical" else symbols_of(columns[p.name], p, True)
        if node.chars:
            node.encode(enc, values, known, own[a.name])
            return
        if id(node) not in steps:
            asked = Steps(rows)
            node.encode(asked, values, known, own[a.name])
            steps[id(node)] = asked.taken
        for step in steps[id(node)]:
            enc.put(*step)

    out: dict[int, np.ndarray] = {}
    todo = [(0, list(range(len(networks))), Sizes(rows))]
    while todo:
        at, which, enc = todo.pop()
        ended = [i for i in which if len(networks[i]) == at]
        if ended:
            out |= dict.fromkeys(ended, enc.sizes())
        apart: dict[int, list[int]] = {}
        for i in which:
            if len(networks[i]) > at:
                apart.setdefault(id(networks[i][at]), []).append(i)
        for left, some in zip(range(len(apart) - 1, -1, -1), apart.values(), strict=True):
            mine = enc.copy() if left else enc
            take(networks[some[0]][at], mine)
            todo.append((at + 1, some, mine))
    return [out[i] for i in range(len(networks))]


def over_budget(spec: TableSpec, structure: Structure, least: dict[str, float], most: dict[str, float], max_cells: int) -> tuple[set[str], bool]:
    """(nodes that lose their parents, whether that is sure) by bounds of the nodes' cells.

    The model budget: the nodes with the most cells lose their parents, all in one go; alone a node has a bounded domain."""
    middle = {n: (least[n] + most[n]) / 2 for n in least}
    dropped: set[str] = set()
    total, low = sum(middle.values()), math.inf
    for n in sorted((n for n, p in structure.parents.items() if p), key=lambda n: -middle[n]):
        if total <= max_cells:
            break
        low = sum(domain_of(spec[x]) if x in dropped else least[x] for x in least)
        dropped.add(n)
        total -= middle[n] - domain_of(spec[n])
    kept = [n for n, p in structure.parents.items() if p and n not in dropped]
    high = sum(domain_of(spec[x]) if x in dropped else most[x] for x in most)
    sure = (high <= max_cells or not kept) and low > max_cells and all(least[d] >= most[k] for d in dropped for k in kept)
    return dropped, sure


def fit_parameters(images: DataFrame, spec: TableSpec, structure: Structure, escape: bool = True, string_order: int = 1, string_sample: int = 2000, max_cells: int = MAX_CELLS) -> Network:
    """Masses of all nodes from the images; character models from a bounded sample of texts."""
    return fit_networks(images, spec, [structure], None, escape, string_order, string_sample, max_cells)[0]


def fit_networks(images: DataFrame, spec: TableSpec, structures: list[Structure], pairs: list[list[tuple[str, str]]] | None = None, escape: bool = True, string_order: int = 1, string_sample: int = 2000,
                 max_cells: int = MAX_CELLS) -> list[Network]:
    """Networks of several structures from one scan of the images (`fit_parameters` of each). `pairs`: keys and what they
    nearly determine, which `with_pairs` is to try, by structure.

    Of families that may be large, the scan counts drawn cells only: where those show that a node goes over the model
    budget by far, it loses its parents without its cells having been counted. The others are counted in a second scan."""
    pairs = pairs or [[] for _ in structures]
    compared = {f for s, ps in zip(structures, pairs, strict=True) if ps for f in key_families(s, ps)}
    families = list(dict.fromkeys([*(f for s in structures for f in s.parents.items()), *compared]))
    drawn = {f for f in families if f[1] and f not in compared and most_cells(spec, f) > max_cells // 2}
    families = list(dict.fromkeys([*families, *((n, ()) for n, _ in families)]))
    counts, more = cells(images, spec, families, frozenset(families.index(f) for f in drawn)).persist(), None
    try:
        number = {r["node"]: r["n"] for r in counts.groupBy("node").agg(F.count(F.lit(1)).alias("n")).collect()}
        if compared:
            price = dict(zip(families, bits_of_counts(counts, spec, families), strict=True))
            structures = [with_pairs(spec, s, ps, price) if ps else s for s, ps in zip(structures, pairs, strict=True)]
        found = {f: float(number.get(i, 0)) for i, f in enumerate(families)}
        # Six deviations on both sides, and more where few cells are drawn.
        least = {f: DRAWN * max(0.0, n - 6 * math.sqrt(n) - 20) if f in drawn else n for f, n in found.items()}
        most = {f: min(DRAWN * (n + 6 * math.sqrt(n) + 40), most_cells(spec, f)) if f in drawn else n for f, n in found.items()}
        bounds = lambda s, by: {f[0]: by[f] for f in s.parents.items()}
        # What alone is more than the budget surely goes, whatever its size; of the rest what is kept or not sure is counted.
        open_ = {}
        for s in structures:
            dropped, sure = over_budget(spec, s, bounds(s, least), bounds(s, most), max_cells)
            open_ |= {f: None for f in s.parents.items() if f in drawn and least[f] <= max_cells and not (sure and f[0] in dropped)}
        wide = list(open_)
        if wide:
            more = cells(images, spec, wide).persist()
            sizes = {r["node"]: r["n"] for r in more.groupBy("node").agg(F.count(F.lit(1)).alias("n")).collect()}
            for i, f in enumerate(wide):
                least[f] = most[f] = float(sizes.get(i, 0))
        made: dict[Family, Node] = {}
        networks = []
        for s in structures:
            dropped, _ = over_budget(spec, s, bounds(s, least), bounds(s, most), max_cells)
            s = Structure({c: () if c in dropped else p for c, p in s.parents.items()})
            wanted = [f for f in s.parents.items() if f not in made]
            for source, listed in ((counts, families), (more, wide)):
                some = {listed.index(f): f for f in wanted if f in listed and (source is more or f not in drawn)}
                if some:
                    table = source.filter(F.col("node").isin(*some)).toArrow()
                    node, key, symbol, cnt = (table.column(c).to_numpy() for c in ("node", "key", "symbol", "cnt"))
                    for i, f in some.items():
                        at = node == i
                        made[f] = fitted_node(images, spec, f, key[at], symbol[at], cnt[at], escape, string_order, string_sample)
            networks.append(Network(spec, [made[f] for f in s.parents.items()]))
        return networks
    finally:
        counts.unpersist()
        if more is not None:
            more.unpersist()


def fitted_node(images: DataFrame, spec: TableSpec, family: Family, key: np.ndarray, symbol: np.ndarray, cnt: np.ndarray, escape: bool, string_order: int, string_sample: int) -> Node:
    n, ps = family
    node = Node.fit(spec[n], tuple(spec[p] for p in ps), key, symbol, cnt, escape)
    if spec[n].kind == "user":
        node.chars = WalkCoder.fit(images, F.col(quoted(n)), spec[n].model)
        node.bits += node.chars.bits
    if spec[n].kind == "string":
        node.chars = fit_characters(images, n, string_order, string_sample)
        node.bits += model_bits(len(node.chars.masses.symbol), len(node.chars.contexts), 1 << 21)
    return node


def fit_characters(images: DataFrame, name: str, order: int, sample: int) -> CharModel:
    """Counts of (context, character) over at most `sample` texts; rarer characters escape."""
    text = F.col(quoted(name))
    # The smallest of a hash of the text, so the same texts whatever the files' layout; each task keeps its own smallest.
    chars = images.filter(text.isNotNull()).select(text.alias("t"), F.xxhash64(text).alias("o")).orderBy("o", "t").limit(sample).select(F.split("t", "").alias("c"))
    at = lambda i, k: F.coalesce(F.get("c", i - k), F.lit(""))
    pairs = F.transform("c", lambda x, i: F.struct(x.alias("x"), F.concat(*[at(i, k) for k in range(order, 0, -1)]).alias("h") if order else F.lit("").alias("h")))
    counts = chars.select(F.explode(pairs).alias("p")).filter("p.x <> ''").groupBy("p.h", "p.x").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").orderBy(F.desc("n")).limit(500_000).collect()
    cells = []
    for r in counts:
        context = 0
        for ch in r["h"]:
            context = (context % (1 << 21)) << 21 | ord(ch)
        cells.append((context if order else 0, ord(r["x"]), r["n"]))
    return CharModel.fit(order, cells)

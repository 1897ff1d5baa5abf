"""Cost-balanced sequence packing.

Attention over a packed piece of n tokens costs `linear * n + quadratic * n^2`. Documents are taken in descending
estimated cost and each goes to the open sequence with the lowest cost so far that still has room. What fits nowhere
is cut over the remaining room, cheapest sequences first, so only the last sequence of a group can be short.

The plan is map-only: a task tokenises the rows of its partition in order, closes a group every `group_tokens`
tokens and packs it, so memory is bounded by the group and no text is shuffled. Group size does not depend on the
input, and a repeated task packs the same rows the same way (sequence ids come from the partition number and a
counter within it).

Defined cases: null and empty texts are one end token; a document longer than a sequence gives full sequences and a
rest; repeated rows are packed each on its own; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common

CAPACITY = 2048
END_ID = 1
GROUP_TOKENS = 4_000_000
LINEAR_COST = 1.0
QUADRATIC_COST = 1.0 / 2048

SCHEMA = ("doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, "
          "sequence_tokens long, sequence_cost double")

#: Two white-space characters in a row, with those beyond ASCII.
_spaces = r"[\s\x{1c}-\x{1f}\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]{2}"
_encoders: dict = {}


def encoder(path: str):
    """(whole texts -> id lists, space-led chunks end to end -> ids and byte length of each id) of a tokenizer file.

    Special tokens' strings count as ordinary text. Within chunks no two white-space characters meet, so the
    look-ahead of the published pattern can't matter there and a plain, faster pattern gives the same pieces.
    """
    if path not in _encoders:
        if path.endswith(".tiktoken"):
            import base64

            import public_tokenizers
            import tiktoken

            with open(path, "rb") as lines:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            lengths = np.zeros(max(ranks.values()) + 1, np.int64)
            lengths[list(ranks.values())] = [len(k) for k in ranks]
            make = lambda name, pattern: tiktoken.Encoding(name, pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
            whole, plain = make("whole", public_tokenizers.PATTERN), make("plain", public_tokenizers.PATTERN.replace(r"\s+(?!\S)|", ""))

            def chunks(joined: str) -> tuple[np.ndarray, np.ndarray]:
                ids = plain.encode_to_numpy(joined, disallowed_special=()).astype(np.uint32)
                return ids, lengths[ids]

            _encoders[path] = (lambda texts: [whole.encode_ordinary(t) for t in texts]), chunks
        else:
            import os

            os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
            from tokenizers import Tokenizer

            tok = Tokenizer.from_file(path)
            tok.encode_special_tokens = True
            _encoders[path] = (lambda texts: [e.ids for e in tok.encode_batch(texts, add_special_tokens=False)]), None
    return _encoders[path]


def encode_texts(texts: list[str], path: str, end_id: int | None = END_ID) -> tuple[np.ndarray, np.ndarray]:
    """Token ids of all texts end to end, and the bounds of each text among them.

    A space between two non-space characters always starts a new word for the tokenizer, so texts are cut there and
    each distinct chunk is encoded once; texts with other white space next to a space are encoded whole.
    """
    encode, encode_chunks = encoder(path)
    chunks = pc.split_pattern(pa.array(texts, pa.large_string()), " ")
    starts = chunks.offsets.to_numpy().astype(np.int64)
    counts = np.diff(starts)
    coded = chunks.flatten().dictionary_encode()
    place = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    odd = pc.or_(pc.not_equal(pc.utf8_trim_whitespace(coded.dictionary), coded.dictionary), pc.match_substring_regex(coded.dictionary, _spaces))
    odd = pc.or_(odd, pc.equal(coded.dictionary, "")).to_numpy(zero_copy_only=False)
    is_whole = np.full(len(texts), encode_chunks is None)
    if len(texts):
        is_whole |= np.logical_or.reduceat(odd[place], starts[:-1])
    plain, whole = np.flatnonzero(~is_whole).tolist(), np.flatnonzero(is_whole).tolist()
    if whole:
        keep = np.repeat(~is_whole, counts)
        coded = coded.filter(pa.array(keep)).cast(pa.large_string()).dictionary_encode()
        place = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        counts = counts[plain]
    starts = np.cumsum(counts) - counts
    distinct = coded.dictionary
    flat, size = np.zeros(0, np.uint32), np.zeros(0, np.int64)
    if len(distinct):
        space, nothing = pa.scalar(" ", pa.large_string()), pa.scalar("", pa.large_string())
        led = pc.binary_join_element_wise(space, distinct, nothing)
        joined = led.buffers()[2].to_pybytes()[: int(pc.sum(pc.binary_length(led)).as_py())].decode()
        flat, spans = encode_chunks(joined)
        ends = np.cumsum(pc.binary_length(distinct).to_numpy() + 1)
        size = np.diff(np.searchsorted(np.cumsum(spans), ends, side="right"), prepend=0)
    # A text's first chunk has no space before it, so these are encoded apart, like the texts taken whole.
    apart_lists = encode([texts[i].partition(" ")[0] for i in plain] + [texts[i] for i in whole])
    place[starts] = len(distinct) + np.arange(len(plain))
    place = np.concatenate([place, len(distinct) + len(plain) + np.arange(len(whole))])
    counts = np.concatenate([counts, np.ones(len(whole), np.int64)])
    size = np.concatenate([size, np.fromiter(map(len, apart_lists), np.int64, len(apart_lists))])
    flat = np.concatenate([flat, np.fromiter((i for one in apart_lists for i in one), np.uint32)])

    at = np.cumsum(size) - size
    piece_size = size[place]
    ids = flat[np.repeat(at[place] - (np.cumsum(piece_size) - piece_size), piece_size) + np.arange(int(piece_size.sum()))]
    text_ends = np.concatenate([[0], np.cumsum(piece_size)])[np.concatenate([[0], np.cumsum(counts)])]
    order = np.empty(len(texts), np.int64)
    order[plain + whole] = np.arange(len(texts))
    begins, ends = text_ends[:-1][order], text_ends[1:][order]
    tail = np.array([] if end_id is None else [end_id], np.uint32)
    parts = [x for b, e in zip(begins, ends, strict=True) for x in (ids[b:e], tail)]
    bounds = np.concatenate([[0], np.cumsum(ends - begins + len(tail))])
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint32)), bounds.astype(np.int64)


def assign(lengths: list[int], capacity: int = CAPACITY, linear: float = LINEAR_COST, quadratic: float = QUADRATIC_COST) -> tuple[list[tuple[int, int, int, int, int]], list[float]]:
    """Pieces (document, start, length, sequence, offset) that cover every document once, and each sequence's cost."""
    cost = lambda n: linear * n + quadratic * n * n
    pieces: list[tuple[int, int, int, int, int]] = []
    costs: list[float] = []
    rest: list[tuple[int, int, int]] = []
    for d, n in enumerate(lengths):
        full = n // capacity
        for k in range(full):
            pieces.append((d, k * capacity, capacity, len(costs), 0))
            costs.append(cost(capacity))
        if n % capacity:
            rest.append((n % capacity, d, full * capacity))
    rest.sort(key=lambda r: (-r[0], r[1]))
    base, wanted = len(costs), -(-sum(r[0] for r in rest) // capacity)
    room = [capacity] * wanted
    costs += [0.0] * wanted
    heap = [(0.0, s) for s in range(wanted)]
    cut: list[tuple[int, int, int]] = []
    for n, d, start in rest:
        passed = []
        while heap and room[heap[0][1]] < n:
            passed.append(heapq.heappop(heap))
        if heap:
            c, s = heapq.heappop(heap)
            pieces.append((d, start, n, base + s, capacity - room[s]))
            room[s] -= n
            costs[base + s] = c + cost(n)
            if room[s]:
                heapq.heappush(heap, (costs[base + s], s))
        else:
            cut.append((n, d, start))
        # No later document is longer, so full sequences never return; others wait for shorter documents.
        for entry in passed:
            heapq.heappush(heap, entry)
    open_now = [s for _, s in sorted(heap)]
    for n, d, start in cut:
        while n:
            s = open_now[0]
            m = min(n, room[s])
            pieces.append((d, start, m, base + s, capacity - room[s]))
            room[s] -= m
            costs[base + s] += cost(m)
            n, start = n - m, start + m
            if not room[s]:
                open_now.pop(0)
    return pieces, costs


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, group_tokens: int = GROUP_TOKENS, end_id: int = END_ID,
         id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece; `with_ids` adds the token ids themselves (array<int>), for a trainer to read."""

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        partition, made = TaskContext.get().partitionId(), 0
        held: list[tuple[list, np.ndarray, np.ndarray]] = []
        held_tokens = 0

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal made, held_tokens
            names = [x for h in held for x in h[0]]
            ids = np.concatenate([h[1] for h in held])
            sizes = np.concatenate([np.diff(h[2]) for h in held])
            begin = np.cumsum(sizes) - sizes
            pieces, costs = assign(sizes.tolist(), capacity)
            used = np.zeros(len(costs), np.int64)
            for _, _, n, s, _ in pieces:
                used[s] += n
            raw = ids.astype("<u4")
            cols = list(zip(*pieces, strict=True))
            crc = [zlib.crc32(raw[begin[d] + a: begin[d] + a + n].tobytes()) for d, a, n, _, _ in pieces]
            seq = np.array(cols[3], np.int64)
            data = [pa.array([names[d] for d in cols[0]], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(crc, pa.int64()),
                    pa.array(sizes[list(cols[0])], pa.int64()), pa.array((partition << 33) + made + seq, pa.int64()), pa.array(cols[4], pa.int64()),
                    pa.array(used[seq], pa.int64()), pa.array(np.array(costs)[seq], pa.float64())]
            if with_ids:
                data.append(pa.array([raw[begin[d] + a: begin[d] + a + n].astype(np.int32) for d, a, n, _, _ in pieces], pa.list_(pa.int32())))
            made += len(costs)
            held.clear()
            held_tokens = 0
            yield pa.RecordBatch.from_arrays(data, names=fields)

        for batch in batches:
            names, texts = batch.column(0).to_pylist(), [t or "" for t in batch.column(1).to_pylist()]
            start = 0
            while start < len(texts):
                # Rows are taken a few million characters at a time, so one batch of long texts stays small.
                stop, chars = start, 0
                while stop < len(texts) and (stop == start or chars + len(texts[stop]) <= group_tokens):
                    chars += len(texts[stop])
                    stop += 1
                ids, bounds = encode_texts(texts[start:stop], tokenizer, end_id)
                held.append((names[start:stop], ids, bounds))
                held_tokens += len(ids)
                start = stop
                if held_tokens >= group_tokens:
                    yield from flush()
        if held:
            yield from flush()

    schema = SCHEMA + (", ids array<int>" if with_ids else "")
    fields = [part.split()[0] for part in schema.split(", ")]
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(packed, schema)


def op7_cost_balanced_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(common.documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"))

"""Language-model scoring over a sharded Elias-Fano n-gram trie.

The model takes a part DISCOUNT off every count seen after a context and gives it to the add-one unigram probability
(absolute discounting; t(h) is how many different words followed the context, which the trie's pointers tell):

    p(w | h) = max(c(h, w) - DISCOUNT, 0) / c(h) + DISCOUNT * t(h) / c(h) * p1(w),   p1(w) = (c(w) + 1) / (N + V + 1)

and p1(w) alone after a context never seen.

A corpus' n-grams outgrow any machine, so the trie is cut into shards by a hash of the context and words meet their
shard by one shuffle:

1. Blocks of whole documents are tokenised once and written as compact local ids (scratch table `blocks`).
2. Each block sends every shard its distinct words and (context, word) pairs with their training counts; a pair seen
   often in a block is one entry, so frequent words don't grow the shuffle.
3. A shard adds the counts up, builds its trie (memory-mapped levels, quantised values), looks every distinct word and
   pair of all requests up once by context-relative successor search, and answers each block in the order of its
   request: word counts and value codes.
4. Blocks meet their answers and score their documents.

Shards and blocks grow in number with the corpus and not in size. Everything between the steps is a table in the
shared scratch folder, so a lost executor repeats tasks only.

Defined cases: null and empty texts are one end token; words of a held-out document unknown to training have p1 of
count 0; repeated rows train and score as often as they occur; very long texts are read whole (a block holds at least
one document); a null id comes back null; further columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common
from relcodec.llm.elias_fano import KEY_BITS, Trie, restore

DISCOUNT = 0.75
BLOCK_TOKENS = 500_000
SHARD_TOKENS = 1_000_000
HELD_OUT_MODULUS, HELD_OUT_REMAINDER = 7, 2
#: Hashes of the two marks that no word can have: context before the first word, and end of the text.
BEGIN, END = np.uint64(0x5D4E1A2B3C4D5E6F), np.uint64(0x1F2E3D4C5B6A7988)


def packed(a: np.ndarray) -> bytes:
    """Compact bytes of counts and ids: byte planes compress better than whole numbers."""
    width = 1 if not len(a) or a.max() < 1 << 8 else 2 if a.max() < 1 << 16 else 4
    planes = a.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T
    return bytes([width]) + zlib.compress(np.ascontiguousarray(planes).tobytes(), 1)


def unpacked(data: bytes) -> np.ndarray:
    width = data[0]
    planes = np.frombuffer(zlib.decompress(data[1:]), np.uint8).reshape(width, -1)
    return np.ascontiguousarray(planes.T).view(f"<u{width}").ravel().astype(np.int64)


def tokenised(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(local ids of all words end to end, words per text, 64-bit hash of each local id by falling frequency)."""
    split = pc.ascii_split_whitespace(pc.ascii_lower(pa.array(texts, pa.large_string())))
    flat = split.flatten()
    real = pc.not_equal(flat, "")
    ends = np.concatenate([[0], np.cumsum(real.to_numpy(zero_copy_only=False))])[split.offsets.to_numpy()]
    coded = flat.filter(real).dictionary_encode()
    ids = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    hashes = np.fromiter((xxhash.xxh64_intdigest(w) for w in coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    order = np.argsort(-np.bincount(ids, minlength=len(hashes)), kind="stable")
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    return place[ids] if len(ids) else ids, np.diff(ends), hashes[order]


def blocks_of(docs: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """block_id, n_tokens, body: documents (doc_id, text, held_out) as blocks of about block_tokens tokens."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        partition, made = TaskContext.get().partitionId(), 0
        ids: list = []
        texts: list[str] = []
        held: list = []
        chars = 0

        def flush() -> pa.RecordBatch:
            nonlocal made, chars
            words, sizes, hashes = tokenised(texts)
            body = pickle.dumps({"ids": np.array([-1 if i is None else i for i in ids], np.int64), "null": np.array([i is None for i in ids]), "held": np.array(held, bool), "sizes": packed(sizes), "words": packed(words), "hashes": hashes.tobytes()})
            made += 1
            out = pa.RecordBatch.from_arrays([pa.array([(partition << 24) + made], pa.int64()), pa.array([len(words) + len(texts)], pa.int64()), pa.array([body], pa.binary())], names=["block_id", "n_tokens", "body"])
            ids.clear(), texts.clear(), held.clear()
            chars = 0
            return out

        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                # A few rows at a time become Python objects.
                for i, t, h in zip(*(c.to_pylist() for c in batch.slice(at, 500).columns), strict=True):
                    ids.append(i), texts.append(t or ""), held.append(h)
                    chars += len(t or "") + 1
                    if chars >= block_tokens * 6:
                        yield flush()
        if texts:
            yield flush()

    return docs.select("doc_id", "text", "held_out").mapInArrow(cut, "block_id long, n_tokens long, body binary")


class Block:
    """A block's documents with its distinct words and pairs, in the order in which shards are asked."""

    def __init__(self, body: bytes, shards: int):
        raw = pickle.loads(body)
        self.ids, self.null, self.held = raw["ids"], raw["null"], raw["held"]
        sizes, words = unpacked(raw["sizes"]), unpacked(raw["words"])
        hashes = np.concatenate([np.frombuffer(raw["hashes"], np.uint64), [BEGIN, END]])
        begin, end = len(hashes) - 2, len(hashes) - 1
        # The words of each text with its end mark, and each token's context.
        self.sizes = sizes + 1
        stops = np.cumsum(self.sizes)
        self.token = np.full(int(self.sizes.sum()), end, np.int64)
        inner = np.ones(len(self.token), bool)
        inner[stops - 1] = False
        self.token[inner] = words
        context = np.empty_like(self.token)
        context[1:] = self.token[:-1]
        context[stops - self.sizes] = begin
        trains = np.repeat(~self.held, self.sizes)
        # Words in the order (shard, hash); contexts are words too, so `begin` is asked for as well.
        shard = ((hashes >> np.uint64(33)) % np.uint64(shards)).astype(np.int64)
        order = np.lexsort((hashes, shard))
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.word_hash, self.word_shard = hashes[order], shard[order]
        self.token, context = place[self.token], place[context]
        self.word_count = np.bincount(self.token, trains, len(order)).astype(np.int64)
        # Pairs in the order (context, hash of the word).
        key = context * len(order) + self.token
        distinct, self.pair = np.unique(key, return_inverse=True)
        of, word = distinct // len(order), distinct % len(order)
        short = self.word_hash[word] >> np.uint64(64 - KEY_BITS)
        sort = np.lexsort((short, of))
        back = np.empty(len(sort), np.int64)
        back[sort] = np.arange(len(sort))
        self.pair = back[self.pair]
        self.pair_context, self.pair_short = of[sort], short[sort]
        self.pair_count = np.bincount(self.pair, trains, len(sort)).astype(np.int64)
        self.context = context

    def slices(self) -> Iterator[tuple[int, slice, slice]]:
        """(shard, its words, its pairs) for every shard asked."""
        starts = np.flatnonzero(np.diff(self.word_shard, prepend=-1))
        for a, b in zip(starts, np.append(starts[1:], len(self.word_shard)), strict=True):
            yield int(self.word_shard[a]), slice(a, b), slice(*np.searchsorted(self.pair_context, [a, b]))


def requests(blocks: DataFrame, shards: int) -> DataFrame:
    def asked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                block_id = batch.column(0)[at].as_py()
                b = Block(batch.column(1)[at].as_py(), shards)
                rows = []
                for shard, w, p in b.slices():
                    fan = np.bincount(b.pair_context[p] - w.start, minlength=w.stop - w.start)
                    short = b.pair_short[p].view(np.uint8).reshape(-1, 8)[:, : KEY_BITS // 8]
                    rows.append((shard, block_id, pickle.dumps((b.word_hash[w].tobytes(), packed(b.word_count[w]), packed(fan), np.ascontiguousarray(short).tobytes(), packed(b.pair_count[p])))))
                columns = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.int64(), pa.binary()), strict=True)], names=["shard", "block_id", "ask"])

    return blocks.select("block_id", "body").mapInArrow(asked, "shard int, block_id long, ask binary")


def answered(frame: pd.DataFrame, discount: float) -> pd.DataFrame:
    """One shard: its trie from all requests, and an answer to each."""
    asks = [pickle.loads(x) for x in frame["ask"]]
    words = [np.frombuffer(a[0], np.uint64) for a in asks]
    fans = [unpacked(a[2]) for a in asks]
    shorts = []
    for a in asks:
        wide = np.zeros((len(a[3]) // (KEY_BITS // 8), 8), np.uint8)
        wide[:, : KEY_BITS // 8] = np.frombuffer(a[3], np.uint8).reshape(-1, KEY_BITS // 8)
        shorts.append(wide.view(np.uint64).ravel())
    word, at = np.unique(np.concatenate(words), return_inverse=True)
    count = np.bincount(at, np.concatenate([unpacked(a[1]) for a in asks]), len(word)).astype(np.int64)
    # Every distinct pair once, in the order of the trie; a pair that only held-out texts have is asked for all the same.
    key = (np.repeat(at, np.concatenate(fans)).astype(np.uint64) << np.uint64(KEY_BITS)) | np.concatenate(shorts)
    key, pair = np.unique(key, return_inverse=True)
    n = np.bincount(pair, np.concatenate([unpacked(a[4]) for a in asks]), len(key)).astype(np.int64)
    asked_context, asked_short = (key >> np.uint64(KEY_BITS)).astype(np.int64), key & np.uint64((1 << KEY_BITS) - 1)
    seen = n > 0
    context, short, total = asked_context[seen], asked_short[seen], n[seen]
    # c(h): how often the context was followed by anything.
    after = np.bincount(context, total, len(word))
    first = np.concatenate([[0], np.cumsum(np.bincount(context, minlength=len(word)))]).astype(np.int64)
    # A context that nothing followed leaves everything to the unigrams.
    rest = np.where(after > 0, discount * np.diff(first) / np.maximum(after, 1), 1.0)
    trie = Trie.build(word, first, short, np.log10(rest), np.log10(np.maximum(total - discount, 1e-9) / after[context])).mapped()
    marks = (word == BEGIN)
    known, tokens = int(((count > 0) & ~marks).sum()), int(count[~marks].sum())
    node = trie.find_contexts(word)
    place = trie.find_successors(node[asked_context], asked_short)
    # Indices into plain views of the mapped levels: each distinct word and pair is looked up once for all requests.
    backoff = np.asarray(trie.backoff)[node].astype(np.int64)
    codes = np.where(place >= 0, np.asarray(trie.probability)[place], 0).astype(np.int64) if len(trie.probability) else np.zeros(len(place), np.int64)
    replies = []
    offset = start = 0
    for w, fan in zip(words, fans, strict=True):
        mine, stop = at[offset: offset + len(w)], start + int(fan.sum())
        replies.append(pickle.dumps((packed(count[mine]), packed(backoff[mine]), packed(codes[pair[start: stop]]))))
        offset, start = offset + len(w), stop
    return pd.DataFrame({"shard": frame["shard"], "block_id": frame["block_id"], "known": known, "tokens": tokens, "answer": replies})


def scored(block: pd.DataFrame, answers: pd.DataFrame, shards: int, n: int, v: int) -> pd.DataFrame:
    b = Block(block["body"].iloc[0], shards)
    by_shard = {s: pickle.loads(a) for s, a in zip(answers["shard"], answers["answer"], strict=True)}
    parts = [by_shard[s] for s, _, _ in b.slices()]
    count, backoff, code = (np.concatenate([unpacked(p[k]) for p in parts]) for k in range(3))
    unigram = (count + 1.0) / (n + v + 1.0)
    p = restore(code)[b.pair] + restore(backoff)[b.context] * unigram[b.token]
    starts = np.cumsum(b.sizes) - b.sizes
    per = lambda x: np.add.reduceat(x, starts)
    ids = pd.Series(b.ids, dtype="Int64")
    ids[b.null] = pd.NA
    return pd.DataFrame({
        "doc_id": ids, "held_out": b.held, "n_tokens": b.sizes, "n_known": per((count > 0)[b.token].astype(np.int64)), "train_tokens": n,
        "base_score": per(np.log10(unigram)[b.token]), "score": per(np.log10(p))})


def score(docs: DataFrame, discount: float = DISCOUNT, block_tokens: int = BLOCK_TOKENS, shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """Scores every row of docs (doc_id, text, held_out); rows that aren't held out are the training corpus."""
    blocks = common.materialise(blocks_of(docs, block_tokens))
    total = blocks.agg(F.sum("n_tokens")).first()[0] or 0
    shards = max(8, -(-total // shard_tokens))
    answers = requests(blocks, shards).groupBy("shard").applyInPandas(
        lambda frame: answered(frame, discount), "shard int, block_id long, known long, tokens long, answer binary")
    answers = common.materialise(answers)
    sums = answers.groupBy("shard").agg(F.max("known").alias("known"), F.max("tokens").alias("tokens")).agg(F.sum("known"), F.sum("tokens")).first()
    v, n = int(sums[0] or 0), int(sums[1] or 0)
    return blocks.select("block_id", "body").groupBy("block_id").cogroup(answers.select("block_id", "shard", "answer").groupBy("block_id")).applyInPandas(
        lambda a, b: scored(a, b, shards, n, v), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op3_elias_fano_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    return score(docs.select("doc_id", "text", (common.fold(F.col("doc_id"), HELD_OUT_MODULUS) == HELD_OUT_REMAINDER).alias("held_out")))

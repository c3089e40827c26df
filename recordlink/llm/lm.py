"""Language-model scores from an n-gram trie in Elias-Fano coded, memory-mapped levels.

The model is an order-3 back-off mixture with absolute discounting: at each level
p(w | h) = alpha(h w) + gamma(h) p(w | shorter h), ending in unigrams mixed with a uniform share for an unknown word.
A level's discount comes from its n-grams seen once and twice in the whole corpus, and the steps of quantised numbers are the
same everywhere: scores do not depend on the number of shards.

Files in the shared folder (shards of bounded size, so nothing is broadcast but their number and first ids):

* vocabulary: sorted 64-bit word hashes with exact counts; a word's id is its rank.
* level 2: for each word, the ids of its successors; level 3: for each bigram (by its place in level 2), its successors as
  places among those of its second word, which are small numbers.  Both hold, in order of contexts, Elias-Fano coded
  pointers (where each context's successors start), bit-packed successors, and quantised log10 alphas and gammas.

A lookup finds its context's range through the pointers and searches the successors there.  A sequence needs one lookup a
level and token: the place of (w1, w2) in level 2 is the context of w3, and that of (w2, w3) gives the relative id.

N-grams are counted without a row each: a task sends every shard one block of its sorted distinct keys with counts.  Shards are
cut by counts, at contexts.  A context that alone has more tokens than a shard should (a frequent word) is a shard of several parts by
successor, so that no task merges all its blocks.  Parts are merged first and written down (one pass), and only when the
corpus's discount is known are they joined to a shard's distinct n-grams and coded (a second pass over these files, which
then go).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Stand for the end of a text and its beginning; words hold no blanks.
END, BEGIN = "\n", " "
LM_CHUNK = 10 << 20
STEPS = 65535


# ------------------------------------------------------------------ coded arrays


def pack_bits(values: np.ndarray, width: int) -> np.ndarray:
    """Unsigned integers of ``width`` bits in a row, in 64-bit words."""
    n = len(values)
    out = np.zeros((n * width + 63 >> 6) + 1, np.uint64)
    if not n or not width:
        return out
    at = np.arange(n, dtype=np.int64) * width
    word, shift = at >> 6, (at & 63).astype(np.uint64)
    v = values.astype(np.uint64)
    # Values that start in one word are disjoint there, so sums are unions.
    starts = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
    out[word[starts]] = np.bitwise_or.reduceat(v << shift, starts)
    over = (shift + np.uint64(width)) > 64
    out[word[over] + 1] |= v[over] >> (np.uint64(64) - shift[over])
    return out


def get_bits(words: np.ndarray, width: int, index: np.ndarray) -> np.ndarray:
    if not width:
        return np.zeros(len(index), np.int64)
    at = index * width
    word, shift = at >> 6, (at & 63).astype(np.uint64)
    low = words[word] >> shift
    high = words[word + 1] << np.uint64(1) << (np.uint64(63) - shift)  # in two steps: 64 places at once are undefined
    return ((low | high) & np.uint64((1 << width) - 1)).view(np.int64)


def select_in_word(word: np.ndarray, k: np.ndarray) -> np.ndarray:
    """The position of the k-th one (from 0) in each 64-bit word."""
    pos = np.zeros(len(word), np.uint64)
    k = k.astype(np.uint64)
    for half in (32, 16, 8, 4, 2, 1):
        ones = np.bitwise_count(word >> pos & np.uint64((1 << half) - 1)).astype(np.uint64)
        skip = k >= ones
        k = np.where(skip, k - ones, k)
        pos = np.where(skip, pos + np.uint64(half), pos)
    return pos.astype(np.int64)


class EliasFano:
    """A monotone sequence: low bits packed, high bits in unary, with the number of ones before each eight words."""

    BLOCK = 8

    def __init__(self, low: np.ndarray, high: np.ndarray, before: np.ndarray, width: int, n: int) -> None:
        self.low, self.high, self.before, self.width, self.n = low, high, before, width, n

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        n = len(values)
        top = int(values[-1]) if n else 0
        width = max(0, (top // max(1, n)).bit_length() - 1)
        at = (values >> width) + np.arange(n)
        words = ((int(at[-1]) >> 6) + 1 if n else 0) + cls.BLOCK
        words += -words % cls.BLOCK
        bits = np.zeros(words * 64, bool)
        bits[at] = True
        high = np.packbits(bits, bitorder="little").view(np.uint64)
        ones = np.bitwise_count(high).reshape(-1, cls.BLOCK).sum(1, dtype=np.int64)
        return cls(pack_bits(values & ((1 << width) - 1), width), high, np.cumsum(ones) - ones, width, n)

    def arrays(self, name: str) -> dict[str, np.ndarray]:
        return {f"{name}_low": self.low, f"{name}_high": self.high, f"{name}_before": self.before, f"{name}_shape": np.array([self.width, self.n])}

    @classmethod
    def of(cls, a: dict[str, np.ndarray], name: str) -> EliasFano:
        return cls(a[f"{name}_low"], a[f"{name}_high"], a[f"{name}_before"], int(a[f"{name}_shape"][0]), int(a[f"{name}_shape"][1]))

    def get(self, index: np.ndarray) -> np.ndarray:
        """The values at the indices."""
        if not len(index):
            return np.empty(0, np.int64)
        block = np.searchsorted(self.before, index, side="right") - 1
        rest = index - self.before[block]
        word = block * self.BLOCK
        for _ in range(self.BLOCK - 1):  # to the word in the block that holds it
            ones = np.bitwise_count(self.high[word]).astype(np.int64)
            on = rest >= ones
            if not on.any():
                break
            rest, word = np.where(on, rest - ones, rest), word + on
        at = word * 64 + select_in_word(self.high[word], rest)
        return (at - index << self.width) | get_bits(self.low, self.width, index)

    def ranges(self, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The values at the indices, which increase, and at the ones after them; neighbours are read once."""
        if not len(index):
            return np.empty(0, np.int64), np.empty(0, np.int64)
        alone = np.append(index[1:] != index[:-1] + 1, True)
        place = np.arange(len(index)) + np.cumsum(alone) - alone
        every = np.empty(len(index) + int(alone.sum()), np.int64)
        every[place] = index
        every[place[alone] + 1] = index[alone] + 1
        values = self.get(every)
        return values[place], values[place + 1]


#: Quantised numbers lie between 10^-FLOOR and 1.
FLOOR = 16.0


def quantise(values: np.ndarray) -> np.ndarray:
    """16-bit steps of log10 values, rounded down: sums of probabilities never exceed 1."""
    return np.floor((values + FLOOR) * (STEPS / FLOOR)).clip(0, STEPS).astype(np.uint16)


_RESTORED = 10.0 ** (np.arange(STEPS + 1) * (FLOOR / STEPS) - FLOOR)


def restore(steps: np.ndarray) -> np.ndarray:
    return _RESTORED[steps]


def discount(once: int, twice: int) -> float:
    """What is taken off each count, from the numbers of n-grams seen once and twice."""
    return min(0.95, max(0.05, once / (once + 2 * twice))) if once + twice else 0.5


def level_blob(contexts: int, context: np.ndarray, child: np.ndarray, count: np.ndarray, d: float) -> bytes:
    """One shard of a level; rows are sorted by (context, child), contexts run from 0 to ``contexts`` - 1."""
    n = len(child)
    fanout = np.bincount(context, minlength=contexts) if contexts else np.empty(0, np.int64)
    start = np.concatenate(([0], np.cumsum(fanout))).astype(np.int64)
    total = np.bincount(context, weights=count, minlength=contexts)
    alpha = quantise(np.log10((count - d) / total[context]) if n else np.empty(0))
    used = fanout > 0
    gamma = quantise(np.log10(np.where(used, d * fanout / np.where(used, total, 1), 1.0)))
    width = int(child.max()).bit_length() if n else 0
    return common.pack({"ids": pack_bits(child, width), "width": np.array([width]), "alpha": alpha, "gamma": gamma} | EliasFano.build(start).arrays("start"))


def cuts(tokens: np.ndarray, step: int) -> list[tuple[int, int]]:
    """(first, tokens) of runs of neighbouring contexts with about ``step`` tokens each; a context with more is a run of its own."""
    if not len(tokens):
        return []
    big = tokens >= step
    run = np.cumsum(np.where(big, 0, tokens)) // step * 2
    edge = np.concatenate(([True], (run[1:] != run[:-1]) | big[1:] | big[:-1]))
    first = np.flatnonzero(edge)
    return list(zip(first.tolist(), np.add.reduceat(tokens, first).tolist(), strict=True))


def shards_of(runs: list[tuple[int, int]], contexts: int, shard_tokens: int) -> tuple[np.ndarray, np.ndarray]:
    """(first context, parts) of each shard: neighbouring runs are joined up to ``shard_tokens``; a run with more is dealt to parts."""
    first, size = [], []
    for at, n in sorted(runs):
        if first and size[-1] + n <= shard_tokens:
            size[-1] += n
        else:
            first.append(at if first else 0)
            size.append(n)
    return np.array(first or [0], np.int64), np.array([max(1, -(-n // shard_tokens)) for n in size or [0]], np.int64)


class Level:
    """The shards of one level; shard s holds the contexts from ``context_first[s]``, its nodes count from ``node_first[s]``."""

    def __init__(self, folder: str, context_first: np.ndarray, node_first: np.ndarray) -> None:
        self.folder, self.context_first, self.node_first = folder, context_first, node_first

    def shard_of(self, context: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.context_first, context, side="right") - 1

    def lookup(self, context: np.ndarray, child: np.ndarray | None) -> tuple[np.ndarray, ...]:
        """For distinct or repeated (context, child), contexts >= 0, child -1 for none: (node or -1, first node of
        the context, alpha or 0, gamma; gamma is 1 where the context has no successors)."""
        q = len(context)
        node, first = np.full(q, -1, np.int64), np.zeros(q, np.int64)
        alpha, gamma = np.zeros(q), np.ones(q)
        if not q:
            return node, first, alpha, gamma
        # Shards are ranges of contexts: one order serves for shards, contexts and their repeats.
        order = np.argsort(context)
        ordered = context[order]
        edges = np.append(np.searchsorted(ordered, self.context_first), q)
        for s in np.flatnonzero(np.diff(edges)).tolist():
            own = order[edges[s] : edges[s + 1]]
            a = common.unpack(common.map_file(f"{self.folder}/{s}"))
            c = ordered[edges[s] : edges[s + 1]] - self.context_first[s]
            fresh = np.concatenate(([True], c[1:] != c[:-1]))
            back = np.cumsum(fresh) - 1
            lo, end = (x[back] for x in EliasFano.of(a, "start").ranges(c[fresh]))
            first[own] = lo + self.node_first[s]
            has = end > lo
            gamma[own] = np.where(has, restore(a["gamma"][c]), 1.0)
            if child is None:
                continue
            want = child[own]
            live = np.flatnonzero(has & (want >= 0))
            width, ids = int(a["width"][0]), a["ids"]
            lo, hi, want = lo[live], end[live], want[live]
            tail = hi.copy()
            while True:  # the first successor that is not smaller
                open_ = np.flatnonzero(lo < hi)
                if not len(open_):
                    break
                mid = lo[open_] + hi[open_] >> 1
                less = get_bits(ids, width, mid) < want[open_]
                lo[open_] = np.where(less, mid + 1, lo[open_])
                hi[open_] = np.where(less, hi[open_], mid)
            inside = np.flatnonzero(lo < tail)
            inside = inside[get_bits(ids, width, lo[inside]) == want[inside]]
            at, hit = lo[inside], own[live[inside]]
            node[hit] = at + self.node_first[s]
            alpha[hit] = restore(a["alpha"][at])
        return node, first, alpha, gamma


class Vocabulary:
    """Shards of sorted word hashes by their top bits; the ids of shard s count from ``first[s]``."""

    def __init__(self, folder: str, bits: int, first: np.ndarray, seed: int) -> None:
        self.folder, self.bits, self.first, self.seed = folder, bits, first, seed

    def lookup(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(id or -1, count) of each word."""
        h = np.array([xxhash.xxh64_intdigest(w, self.seed) for w in words], np.uint64)
        ids, counts = np.full(len(h), -1, np.int64), np.zeros(len(h), np.int64)
        # In order of hashes shards are ranges, and neighbours are found in neighbouring places.
        order = np.argsort(h)
        h = h[order]
        shard = (h >> np.uint64(64 - self.bits)).astype(np.int64) if self.bits else np.zeros(len(h), np.int64)
        edges = np.searchsorted(shard, np.arange(len(self.first) + 1))
        for s in np.flatnonzero(np.diff(edges)).tolist():
            a = common.unpack(common.map_file(f"{self.folder}/{s}"))
            if not len(a["hash"]):
                continue
            want, own = h[edges[s] : edges[s + 1]], order[edges[s] : edges[s + 1]]
            at = np.minimum(np.searchsorted(a["hash"], want), len(a["hash"]) - 1)
            hit = a["hash"][at] == want
            ids[own[hit]] = at[hit] + self.first[s]
            counts[own[hit]] = a["count"][at[hit]]
        return ids, counts


# ------------------------------------------------------------------ sequences


def sequences(t: common.Tokens, ids: np.ndarray, begin: int, end: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all texts in a row, each as begin, words, end; the place in its text of each)."""
    lengths = t.lengths + 2
    stops = np.cumsum(lengths)
    seq = np.empty(int(stops[-1]) if len(stops) else 0, np.int64)
    place = np.arange(len(seq)) - np.repeat(stops - lengths, lengths)
    inner = np.ones(len(seq), bool)
    inner[stops - lengths], inner[stops - 1] = False, False
    seq[stops - lengths], seq[stops - 1] = begin, end
    seq[inner] = ids[t.codes]
    return seq, place


def _blocks(shard: np.ndarray, key: np.ndarray, count: np.ndarray) -> pa.RecordBatch:
    """Rows (shard, block) of keys sorted within their shards."""
    rows, blobs = [], []
    cuts = np.flatnonzero(np.concatenate(([True], shard[1:] != shard[:-1], [True]))) if len(shard) else np.array([0])
    codec = pa.Codec("zstd", 1)
    for lo, hi in zip(cuts, cuts[1:], strict=False):
        k = key[lo:hi]
        steps = np.diff(k, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T
        body = [np.ascontiguousarray(steps).tobytes(), count[lo:hi].astype(np.uint32).view(np.uint8).reshape(-1, 4).T.tobytes()]
        rows.append(int(shard[lo]))
        blobs.append((hi - lo).item().to_bytes(8, "little") + codec.compress(b"".join(body), asbytes=True))
    return pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(blobs, pa.binary())], names=["shard", "block"])


def _merge(blocks: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys of all blocks, sorted, and their summed counts."""
    codec, keys, counts = pa.Codec("zstd", 1), [], []
    for b in blocks:
        n = int.from_bytes(b[:8], "little")
        raw = np.frombuffer(codec.decompress(b[8:], decompressed_size=12 * n, asbytes=True), np.uint8)
        keys.append(np.cumsum(np.ascontiguousarray(raw[: 8 * n].reshape(8, n).T).view(np.uint64).ravel(), dtype=np.uint64))
        counts.append(np.ascontiguousarray(raw[8 * n :].reshape(4, n).T).view(np.uint32).ravel())
    key, count = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(key, kind="stable")
    key, count = key[order], count[order].astype(np.int64)
    cuts = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    return key[cuts], np.add.reduceat(count, cuts)


def _count_grams(context: np.ndarray, child: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct (context, child), sorted, and their counts."""
    if not len(context):
        return context, child, np.empty(0, np.int64)
    if int(context.max()) >> 31:  # both do not fit in 64 bits
        order = np.lexsort((child, context))
        context, child = context[order], child[order]
    else:
        key = np.sort(context << 32 | child)
        context, child = key >> 32, key & 0xFFFFFFFF
    at = np.flatnonzero(np.concatenate(([True], (context[1:] != context[:-1]) | (child[1:] != child[:-1]))))
    return context[at], child[at], np.diff(np.append(at, len(context)))


def _hash_words(seed: int, bits: int):
    def run(batches):
        for b in batches:
            h = np.array([xxhash.xxh64_intdigest(w.encode(), seed) for w in b.column(0).to_pylist()], np.uint64)
            shard = (h >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(h), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(shard), pa.array(h.view(np.int64)), b.column(1)], names=["shard", "hash", "n"])

    return run


RUNS = "array<struct<first: long, tokens: long>>"


def _runs(runs: list[tuple[int, int]]) -> pa.Array:
    """A list of runs as a column of one row."""
    return pa.array([[{"first": a, "tokens": n} for a, n in runs]], pa.list_(pa.struct([("first", pa.int64()), ("tokens", pa.int64())])))


def _store_words(folder: str, step: int):
    def store(table: pa.Table) -> pa.Table:
        h, n = np.asarray(table["hash"]).view(np.uint64), np.asarray(table["n"])
        order = np.argsort(h)
        h, n = h[order], n[order]
        s = table["shard"][0].as_py()
        common.put_file(f"{folder}/{s}", common.pack({"hash": h, "count": n}))
        return pa.table({"shard": [s], "n": [len(h)], "same": [int((h[1:] == h[:-1]).sum())], "runs": _runs(cuts(n, step))})

    return store


class TrieModel:
    """Vocabulary, level 2 and level 3 of the training rows of a table."""

    def __init__(self, df: DataFrame, train: tuple[int, set[int]] | None = None, id_col: str = "doc_id", text_col: str = "text", shard_tokens: int = 3_000_000) -> None:
        """Learn from the rows whose crc32(id as text) modulo ``train[0]`` is not in ``train[1]`` (None: from all).

        A shard takes about ``shard_tokens`` tokens' n-grams; more tokens give more shards, not larger ones.
        """
        spark = df.sparkSession
        self.train, self.id_col, self.text_col = train, id_col, text_col
        self.folder = common.shared_folder(spark, "lm")
        src = df.select(F.col(id_col).cast("string").alias("id"), F.col(text_col).cast("string").alias("text"))
        runs = self._count_words(src, shard_tokens)
        if self.words_total + 2 >> 32:
            raise ValueError("more than 2^32 words: their ids would not fit")
        self.level2, runs = self._build(src, "bigrams", runs, self.words_total + 2, None, shard_tokens)
        self.level3, _ = self._build(src, "trigrams", runs, max(1, self.level2.node_total), self.level2, shard_tokens)

    # -- training

    def _training(self, part: pa.RecordBatch) -> pa.Array:
        if self.train is None:
            return part.column(1)
        mod, out = self.train
        return part.column(1).filter(pa.array(~np.isin(common.crc_mod(part.column(0), mod), list(out))))

    def _count_words(self, src: DataFrame, shard_tokens: int) -> list[tuple[int, int]]:
        """Write the vocabulary; the runs of word ids by tokens."""
        training = self._training

        def run(part: pa.RecordBatch) -> pa.RecordBatch:
            texts = training(part)
            t = common.tokenize(texts)
            words = pa.concat_arrays([t.words.cast(pa.string()), pa.array([END, BEGIN], pa.string())])
            n = np.concatenate([np.bincount(t.codes, minlength=len(t.words)), [len(t), len(t)]])
            return pa.RecordBatch.from_arrays([words, pa.array(n.astype(np.int64))], names=["word", "n"])

        counted = common.settle(_map(src, run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).where("n > 0"))
        real = counted.where(F.col("word") != BEGIN).agg(F.count("*"), F.sum("n")).first()
        #: V and N: distinct words of training texts, the end among them, and all their tokens.
        self.words_total, self.tokens = int(real[0]), int(real[1] or 0)
        bits = max(0, (self.words_total // max(1, shard_tokens // 4)).bit_length())
        for seed in range(8):
            folder = f"{self.folder}/words-{seed}"
            hashed = counted.mapInArrow(_hash_words(seed, bits), "shard long, hash long, n long")
            done = hashed.groupBy("shard").applyInArrow(_store_words(folder, max(1, shard_tokens // 4)), f"shard long, n long, same long, runs {RUNS}").collect()
            if not any(r["same"] for r in done):
                break
        else:
            raise RuntimeError("word hashes collide under every seed")
        sizes = np.zeros(1 << bits, np.int64)
        for r in done:
            sizes[r["shard"]] = r["n"]
        for s in np.flatnonzero(sizes == 0):
            common.put_file(f"{folder}/{s}", common.pack({"hash": np.empty(0, np.uint64), "count": np.empty(0, np.int64)}))
        self.vocabulary = Vocabulary(folder, bits, np.cumsum(sizes) - sizes, seed)
        (self.begin, self.end), _ = self.vocabulary.lookup([BEGIN.encode(), END.encode()])
        return [(int(self.vocabulary.first[r["shard"]]) + a, n) for r in done for a, n in r["runs"]]

    def _build(self, src: DataFrame, name: str, runs: list[tuple[int, int]], contexts: int, lower: Level | None, shard_tokens: int) -> tuple[Level, list[tuple[int, int]]]:
        """Count the level's n-grams and write its shards, cut by ``runs``; gives the level and the runs of its nodes."""
        training, vocabulary, begin, end = self._training, self.vocabulary, int(self.begin), int(self.end)
        folder = f"{self.folder}/{name}"
        edges, parts = shards_of(runs, contexts, shard_tokens)
        slot = np.cumsum(parts) - parts  # the parts of all shards in a row
        owner = np.repeat(np.arange(len(edges)), parts)

        def run(part: pa.RecordBatch) -> pa.RecordBatch | None:
            t = common.tokenize(training(part))
            if not len(t):
                return None
            ids, _ = vocabulary.lookup(t.words.cast(pa.large_binary()).to_pylist())
            seq, place = sequences(t, ids, begin, end)
            context, child = seq[:-1], seq[1:]
            inner = place[1:] > 0
            if lower is not None:
                context, child, inner = _trigrams(lower, seq, place)
            context, child, n = _count_grams(context[inner], child[inner])
            shard = np.searchsorted(edges, context, side="right") - 1
            key = (context - edges[shard]).astype(np.uint64) << np.uint64(32) | child.astype(np.uint64)
            piece = slot[shard] + child * 2654435761 % 4294967296 % parts[shard]
            if (parts[shard] > 1).any():
                order = np.argsort(piece, kind="stable")
                piece, key, n = piece[order], key[order], n[order]
            return _blocks(piece, key, n)

        def merge(table: pa.Table) -> pa.Table:
            piece = table["shard"][0].as_py()
            key, n = _merge(table["block"].to_pylist())
            # Counts of a corpus are small numbers but for a few: a byte each, and the others in full.
            large = np.flatnonzero(n > 254)
            small = n.copy()
            small[large] = 255
            body = pa.Codec("zstd", 1).compress(np.diff(key, prepend=np.uint64(0)).tobytes() + small.astype(np.uint8).tobytes(), asbytes=True)
            common.put_file(f"{folder}/part-{piece}", common.pack({"n": np.array([len(key)]), "body": np.frombuffer(body, np.uint8), "large": n[large]}))
            return pa.table({"piece": [piece], "once": [int((n == 1).sum())], "twice": [int((n == 2).sum())]})

        counted = _map(src, run, "shard long, block binary").groupBy("shard").applyInArrow(merge, "piece long, once long, twice long").collect()
        d = discount(sum(r["once"] for r in counted), sum(r["twice"] for r in counted))
        written = {r["piece"] for r in counted}
        last, step = np.append(edges[1:], contexts), max(1, shard_tokens // 4)

        def code(batches):
            for b in batches:
                for s in b.column(0).to_pylist():
                    own = [p for p in range(int(slot[s]), int(slot[s] + parts[s])) if p in written]
                    target = f"{folder}/{s}"
                    got = [x for p in own if (x := common.read_file(f"{folder}/part-{p}")) is not None]
                    if len(got) == len(own):
                        keys, counts = zip(*map(_part, got), strict=True) if got else ((np.empty(0, np.uint64),), (np.empty(0, np.int64),))
                        key, n = np.concatenate(keys), np.concatenate(counts)
                        order = np.argsort(key)
                        key, n = key[order], n[order]
                        context = (key >> np.uint64(32)).astype(np.int64)
                        common.put_file(target, level_blob(int(last[s] - edges[s]), context, (key & np.uint64(0xFFFFFFFF)).astype(np.int64), n, d))
                        common.put_file(f"{target}.runs", common.pack({"n": np.array([len(key)]), "runs": np.array(cuts(n, step), np.int64).ravel()}))
                        for p in own:
                            common.drop_file(f"{folder}/part-{p}")
                    # A task that runs again after its parts have gone finds the shard whole.
                    made = common.unpack(np.frombuffer(common.read_file(f"{target}.runs"), np.uint8))
                    runs = [tuple(x) for x in made["runs"].reshape(-1, 2).tolist()]
                    yield pa.RecordBatch.from_arrays([pa.array([s]), pa.array(made["n"]), _runs(runs)], names=["shard", "n", "runs"])

        spark = src.sparkSession
        many = min(len(edges), max(2 * spark.sparkContext.defaultParallelism, len(edges) // 8))
        sizes, found = np.zeros(len(edges), np.int64), {}
        for r in spark.range(0, len(edges), 1, many).mapInArrow(code, f"shard long, n long, runs {RUNS}").collect():
            sizes[r["shard"]], found[r["shard"]] = r["n"], r["runs"]
        level = Level(folder, edges, np.cumsum(sizes) - sizes)
        level.node_total = int(sizes.sum())
        return level, [(int(level.node_first[s]) + a, n) for s, x in found.items() for a, n in x]

    # -- scoring

    def score_column(self, column: pa.Array) -> dict[str, np.ndarray]:
        t = common.tokenize(column)
        ids, counts = self.vocabulary.lookup(t.words.cast(pa.large_binary()).to_pylist())
        begin, end = int(self.begin), int(self.end)
        # Words are numbered within the chunk first: whatever is known of each distinct one is then read by these numbers.
        codes, place = sequences(t, np.arange(len(t.words)), len(t.words), len(t.words) + 1)
        seq = np.append(ids, [begin, end])[codes]
        _, (end_count,) = self.vocabulary.lookup([END.encode()])
        real = place > 0
        n, v = self.tokens, self.words_total
        d = 0.5
        unseen = (d * v / n if n else 1.0) / (v + 1)
        # Of each distinct word first, then of the tokens; the beginning is never counted.
        counts = np.append(counts, [0, int(end_count)])
        p = (np.where(counts > 0, (counts - d) / max(n, 1), 0.0) + unseen)[codes]
        pair = np.flatnonzero(real)
        b, first, alpha2, gamma2 = _bigrams(self.level2, seq, pair)
        p[pair] = alpha2 + gamma2 * p[pair]
        # A context of two words: the bigram that ends just before.
        node = np.full(len(seq), -1, np.int64)
        node[pair] = b
        start = np.zeros(len(seq), np.int64)
        start[pair] = first
        third = np.flatnonzero(place > 1)
        third = third[node[third - 1] >= 0]
        rel = np.where(node[third] >= 0, node[third] - start[third], -1)
        _, _, alpha3, gamma3 = self.level3.lookup(node[third - 1], rel)
        p[third] = alpha3 + gamma3 * p[third]
        owner = np.cumsum(place == 0) - 1
        size = len(t)
        known = (counts > 0)[codes]  # the beginning's count is 0
        base = np.log10((counts + 0.1) / (n + 0.1 * (v + 1)))[codes]
        return {
            "n_tokens": t.lengths + 1,
            "n_known": np.bincount(owner[known], minlength=size),
            "train_tokens": np.full(size, n),
            "base_score": np.bincount(owner[real], weights=base[real], minlength=size),
            "score": np.bincount(owner[real], weights=np.log10(p[real]), minlength=size),
        }

    def score(self, df: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
        """``keep`` beside n_tokens, n_known, train_tokens, base_score and score of every whole text.

        A null or empty text is its end alone; repeated rows get equal scores; texts of any length are scored whole; an empty table
        gives no rows, and a model of one knows no word; kept columns come back under free names.
        """
        out = {"n_tokens": "long", "n_known": "long", "train_tokens": "long", "base_score": "double", "score": "double"}
        model = self

        def run(column: pa.Array) -> dict[str, pa.Array]:
            return {k: pa.array(v) for k, v in model.score_column(column).items()}

        return common.annotate(df, run, out, list(keep), self.text_col)


def _part(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The keys and counts of one written part."""
    a = common.unpack(np.frombuffer(raw, np.uint8))
    n = int(a["n"][0])
    body = np.frombuffer(pa.Codec("zstd", 1).decompress(a["body"].tobytes(), decompressed_size=9 * n, asbytes=True), np.uint8)
    counts = body[8 * n :].astype(np.int64)
    counts[counts == 255] = a["large"]
    return np.cumsum(body[: 8 * n].view(np.uint64), dtype=np.uint64), counts


def _map(df: DataFrame, fn, schema: str) -> DataFrame:
    return common.map_arrow(df, fn, schema, "text", LM_CHUNK)


def _bigrams(level: Level, seq: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, ...]:
    """Level.lookup of (the one before, the one at) each place; unknown words give no node, and gamma 1 as a context."""
    before, word = seq[at - 1], seq[at]
    code, distinct = pd.factorize(((before + 1) << 32) | (word + 1))  # both are under 2^32 (see TrieModel)
    c, w = (distinct.view(np.uint64) >> np.uint64(32)).astype(np.int64) - 1, (distinct & 0xFFFFFFFF) - 1
    node, first, alpha, gamma = np.full(len(c), -1, np.int64), np.zeros(len(c), np.int64), np.zeros(len(c)), np.ones(len(c))
    known = np.flatnonzero(c >= 0)
    node[known], first[known], alpha[known], gamma[known] = level.lookup(c[known], w[known])
    return node[code], first[code], alpha[code], gamma[code]


def _trigrams(level: Level, seq: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context node, relative id, whether it is a trigram) for each place from the second on."""
    pair = np.flatnonzero(place > 0)
    b, first, _, _ = _bigrams(level, seq, pair)
    node, start = np.full(len(seq), -1, np.int64), np.zeros(len(seq), np.int64)
    node[pair], start[pair] = b, first
    return node[:-1], (node - start)[1:], place[1:] > 1


def held_out_column(df: DataFrame, mod: int, out: set[int], id_col: str = "doc_id"):
    """The same rule on rows: is crc32(id as text) modulo ``mod`` one of ``out``?"""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(mod)).isin(*out)

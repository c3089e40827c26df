import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from recordlink.llm import lm


def words_of(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    return re.findall("[^\x20\x09-\x0d]+", low)


class Brute:
    """The same mixture with dictionaries and exact probabilities (one discount a level)."""

    def __init__(self, texts):
        self.c = [Counter(), Counter(), Counter()]
        for t in texts:
            seq = [lm.BEGIN, *words_of(t), lm.END]
            self.c[0].update(seq[1:])
            self.c[1].update(zip(seq, seq[1:]))
            self.c[2].update(zip(seq, seq[1:], seq[2:]))
        self.n, self.v = sum(self.c[0].values()), len(self.c[0])
        self.total, self.fan, self.d = [None], [None], [0.5]
        for k in (1, 2):
            total, fan = Counter(), Counter()
            for g, x in self.c[k].items():
                total[g[:-1]] += x
                fan[g[:-1]] += 1
            one, two = (sum(x == m for x in self.c[k].values()) for m in (1, 2))
            self.total.append(total)
            self.fan.append(fan)
            self.d.append(min(0.95, max(0.05, one / (one + 2 * two))) if one + two else 0.5)

    def p(self, gram):
        if len(gram) == 1:
            x = self.c[0][gram[0]]
            return (x - 0.5 if x else 0) / max(self.n, 1) + (0.5 * self.v / self.n if self.n else 1) / (self.v + 1)
        k, h = len(gram) - 1, gram[:-1]
        low = self.p(gram[1:])
        if not self.total[k][h]:
            return low
        x = self.c[k][gram]
        return (max(x - self.d[k], 0) if x else 0) / self.total[k][h] + self.d[k] * self.fan[k][h] / self.total[k][h] * low

    def score(self, text):
        seq = [lm.BEGIN, *words_of(text), lm.END]
        return sum(math.log10(self.p(tuple(seq[max(0, i - 2) : i + 1]))) for i in range(1, len(seq)))


def held(doc_id):
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 10 == 0


def test_bits_and_elias_fano():
    rng = np.random.default_rng(3)
    for width in (1, 7, 31, 33, 63):
        v = rng.integers(0, 1 << width, 500)
        assert (lm.get_bits(lm.pack_bits(v, width), width, np.arange(500)) == v).all()
    for n, top in ((1, 1), (5, 3), (1000, 10), (1000, 10**9), (3000, 3000)):
        v = np.sort(rng.integers(0, top, n))
        ef = lm.EliasFano.build(v)
        at = rng.integers(0, n, 200)
        assert (ef.get(at) == v[at]).all()
        assert ef.high.nbytes + ef.low.nbytes < 200 + n * (2.3 + max(0, math.log2(max(1, top / n)))) / 8 + 8 * 20


def test_grams_and_blocks():
    rng = np.random.default_rng(8)
    for shift in (0, 40):  # contexts within 31 bits, and beyond
        context, child = rng.integers(0, 5, 300) << shift, rng.integers(0, 7, 300)
        want = Counter(zip(context.tolist(), child.tolist()))
        c, w, n = lm._count_grams(context, child)
        assert list(zip(c.tolist(), w.tolist())) == sorted(want) and n.tolist() == [want[x] for x in sorted(want)]
    b = lm._blocks(np.array([0, 0, 0, 1]), np.array([1, 3, 9, 1 << 50], np.uint64), np.array([1, 1, 2, 1]))
    blocks = b.column(1).to_pylist()
    got = lm._merge([blocks[0], blocks[0]])
    assert got[0].tolist() == [1, 3, 9] and got[1].tolist() == [2, 2, 4]


def test_shards_are_cut_by_counts():
    tokens = np.array([1, 2, 3, 50, 1, 1, 9, 9, 9, 0, 30])
    runs = lm.cuts(tokens, 10)
    assert [a for a, _ in runs][0] == 0 and sum(n for _, n in runs) == tokens.sum() and (3, 50) in runs and (10, 30) in runs
    first, parts = lm.shards_of(runs, 11, 20)
    edges = np.append(first, 11)
    sizes = [tokens[a:b].sum() for a, b in zip(edges, edges[1:])]
    assert all(n <= 20 * p for n, p in zip(sizes, parts)) and sum(sizes) == tokens.sum() and parts[list(first).index(3)] == 3
    assert lm.shards_of([], 5, 20)[0].tolist() == [0] and lm.cuts(np.empty(0, np.int64), 3) == []


def base_of(text, brute):
    toks = [*words_of(text), lm.END]
    return sum(math.log10((brute.c[0][w] + 0.1) / (brute.n + 0.1 * (brute.v + 1))) for w in toks), len(toks), sum(brute.c[0][w] > 0 for w in toks)


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_scores_match_brute_force(request, which):
    df = request.getfixturevalue(which)
    rows = df.collect()
    brute = Brute([r["text"] for r in rows if not held(r["doc_id"])])
    model = lm.TrieModel(df, train=(10, {0}))
    assert (model.tokens, model.words_total) == (brute.n, brute.v)
    got = model.score(df, keep=("doc_id", "text")).collect()
    assert len(got) == len(rows)
    for r in got:
        base, n, known = base_of(r["text"], brute)
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (n, known, brute.n)
        assert math.isclose(r["base_score"], base, rel_tol=1e-9, abs_tol=1e-9)
        want = brute.score(r["text"])
        assert abs(r["score"] - want) <= 1e-3 * n + 1e-9 and r["score"] <= want + 1e-9


def test_scores_do_not_depend_on_the_shards(docs, odd):
    """One shard, and many with frequent words in several parts: equal to the last digit; and better than the base on held-out rows."""
    for df in (docs, odd):
        models = [lm.TrieModel(df, train=(10, {0}), shard_tokens=n) for n in (3_000_000, 2000)]
        assert df is odd or len(models[1].level3.context_first) > 20 < len(models[1].level2.context_first)
        texts = pa.array([r["text"] for r in df.collect()] + ["the of unseenword the"])
        a, b = (m.score_column(texts) for m in models)
        assert all((a[k] == b[k]).all() for k in a)
    got = [r for r in lm.TrieModel(docs, train=(10, {0}), shard_tokens=2000).score(docs).collect() if held(r["doc_id"])]
    assert sum(r["score"] for r in got) > sum(r["base_score"] for r in got)


def test_a_word_of_many_successors_is_merged_in_parts(spark):
    """One word before half of all words: its successors are counted in several parts, and each probability stays right."""
    df = spark.createDataFrame([(i, " ".join(f"the w{(i * 7 + k) % 90}" for k in range(40))) for i in range(40)], "doc_id long, text string")
    model, own = lm.TrieModel(df, shard_tokens=300), Brute([r["text"] for r in df.collect()])
    ids, _ = model.vocabulary.lookup([b"the"])
    first, parts = lm.shards_of([(0, 5), (int(ids[0]), own.c[0]["the"])], model.words_total, 300)
    assert parts.max() > 1
    for t in ("the w1 the w8", "w3 the", "the the", "the zz the w5"):
        assert abs(model.score_column(pa.array([t]))["score"][0] - own.score(t)) < 2e-3


def test_next_word_probabilities_sum_to_one(spark):
    df = spark.createDataFrame([(1, "a b c a b d"), (2, "b c a"), (3, "a b c c")], "doc_id long, text string")
    model = lm.TrieModel(df)
    own = Brute([r["text"] for r in df.collect()])
    assert math.isclose(sum(own.p(("a", "b", w)) for w in ("a", "b", "c", "d", "zz", lm.END)), 1.0)
    # The model's own: p(w | a b) is what w adds to a text that goes on the same way.
    known = ["a", "b", "c", "d"]
    ids, counts = model.vocabulary.lookup([w.encode() for w in [*known, lm.END]])
    node, start, _, _ = model.level2.lookup(ids[:1].repeat(5), ids)
    ab = model.level2.lookup(ids[:1], ids[1:2])[0]
    b_node, b_start, alpha2, gamma2 = model.level2.lookup(ids[1:2].repeat(5), ids)
    _, _, alpha3, gamma3 = model.level3.lookup(ab.repeat(5), np.where(b_node >= 0, b_node - b_start, -1))
    n, v = model.tokens, model.words_total
    unseen = 0.5 * v / n / (v + 1)
    p1 = (counts - 0.5) / n + unseen
    p3 = alpha3 + gamma3 * (alpha2 + gamma2 * p1)
    rest = gamma3[0] * gamma2[0] * unseen
    assert abs(p3.sum() + rest - 1) < 3e-3 and p3.sum() + rest <= 1
    for t in ("a b c", "a b zz", "", "zz zz", "d"):
        assert abs(model.score_column(pa.array([t]))["score"][0] - own.score(t)) < 1e-3


def test_empty_table(none):
    model = lm.TrieModel(none)
    assert (model.tokens, model.words_total) == (0, 0)
    assert model.score(none).count() == 0
    got = model.score_column(pa.array(["never seen", None]))
    assert got["n_tokens"].tolist() == [3, 1] and np.isfinite(got["score"]).all()


def test_chunks_behind_the_first_are_scored_from_their_own_words(spark):
    """A task cuts its rows at so many bytes; each slice gives what its rows give alone."""
    rows = [(i, f"Word{i % 7} NEXT{i % 5} \u00c9t\u00e9 " * (i % 4 + 1)) for i in range(60)]
    parts = list(lm.common.chunks(pa.RecordBatch.from_pylist([{"text": t} for _, t in rows]), limit=300))
    assert len(parts) > 5
    found = []
    for p in parts:
        t = lm.common.tokenize(p.column(0))
        words = t.words.to_pylist()
        found += [[words[c] for c in t.codes[a:b]] for a, b in zip(t.offsets, t.offsets[1:])]
    assert found == [words_of(t) for _, t in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    brute = Brute([t for i, t in rows if not held(i)])
    column = pa.array([t for _, t in rows]).slice(20, 30)
    got = lm.TrieModel(df, train=(10, {0})).score_column(column)
    for i, (_, t) in enumerate(rows[20:50]):
        base, n, known = base_of(t, brute)
        assert (got["n_tokens"][i], got["n_known"][i]) == (n, known) and math.isclose(got["base_score"][i], base, rel_tol=1e-9)


def test_held_out_rule(odd):
    rows = odd.select("doc_id", lm.held_out_column(odd, 10, {0}).alias("h")).collect()
    assert [r["h"] for r in rows] == [held(r["doc_id"]) for r in rows]


def test_ranges_of_neighbouring_contexts_are_read_once(monkeypatch):
    """A range's end is the next one's start: that place is not looked up twice, and packed numbers of all widths and places come back."""
    rng = np.random.default_rng(3)
    values = np.cumsum(rng.integers(0, 9, 5000))
    coded, get, asked = lm.EliasFano.build(values), lm.EliasFano.get, []
    monkeypatch.setattr(lm.EliasFano, "get", lambda self, i: asked.append(len(i)) or get(self, i))
    for index in (np.arange(4999), np.arange(0, 4999, 2), np.flatnonzero(rng.random(4999) < 0.6), np.array([4998]), np.empty(0, np.int64)):
        lo, end = coded.ranges(index)
        assert (lo == values[index]).all() and (end == values[index + 1]).all()
    assert asked[0] == 5000
    for width in (1, 7, 31, 33, 63):
        v = rng.integers(0, 1 << width, 700)
        assert (lm.get_bits(lm.pack_bits(v, width), width, np.arange(700)) == v).all()


def test_a_chunk_is_numbered_once_and_words_are_looked_up_in_order(docs, monkeypatch):
    model = lm.TrieModel(docs, (10, {0}), shard_tokens=4_000)
    assert len(model.vocabulary.first) > 1
    words = sorted({w.lower() for r in docs.select("text").limit(40).collect() for w in (r["text"] or "").encode().split()})
    asked = [*words, b"no such word", *reversed(words)]
    ids, counts = model.vocabulary.lookup(asked)
    each = [model.vocabulary.lookup([w]) for w in asked]
    assert ids.tolist() == [int(a[0]) for a, _ in each] and counts.tolist() == [int(b[0]) for _, b in each]
    calls, real = [], lm.sequences
    monkeypatch.setattr(lm, "sequences", lambda *a: calls.append(1) or real(*a))
    model.score_column(pa.array(["a few words", None, "no such word at all"]))
    assert len(calls) == 1

import math
import re
from collections import Counter

import numpy as np

from recordlink.llm import quality_rules as q


def brute(text):
    text = text or ""
    words = re.findall("[^\x20\x09-\x0d]+", text)
    lines = [x for x in text.split("\n") if re.search("[^\x20\x09-\x0d]", x)]
    dup = sum(x in lines[:i] for i, x in enumerate(lines))
    win = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = Counter(win)
    cover = {i + k for i, w in enumerate(win) if often[w] > 1 for k in range(3)}
    failed = len(words) < 50 or 100 * len(cover) > 50 * len(words)
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(cover), failed


BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]


def test_base_counts(docs, odd, none):
    for df in (docs, odd):
        rules = q.Rules(q.fit(df))
        rows = q.score(df, rules, [c for c in ("doc_id", "text", "n_words", "Kept") if c in df.columns]).collect()
        assert len(rows) == df.count()
        for r in rows:
            assert tuple(r[c] for c in BASE) == brute(r["text"])
            assert not (r["base_failed"] and r["kept"])
        assert sorted(str(r["doc_id"]) for r in q.keep_good(df, rules).collect()) == sorted(str(r["doc_id"]) for r in rows if r["kept"])
    assert q.fit(none) == {} and q.score(none, q.Rules(), ["doc_id"]).count() == 0


def test_references_count_everything(docs):
    refs = q.fit(docs, top_words=5)
    for lang, ref in refs.items():
        texts = [r["text"] for r in docs.collect() if r["lang"] == lang]
        words = Counter(w for t in texts for w in re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t)))
        best = sorted(words.items(), key=lambda x: (-x[1], x[0].encode()))[:5]
        assert [k.decode() for k in ref.words] == [w for w, _ in best]
        assert ref.word_counts.tolist() == [*(n for _, n in best), sum(words.values()) - sum(n for _, n in best)]
        assert ref.chars.sum() == sum(map(len, texts))


def test_js_distance_by_definition():
    p, m = [1, 0, 1], [0, 1, 1]
    h = lambda v: -sum(x / sum(v) * math.log2(x / sum(v)) for x in v if x)
    mid = [(a / 2 + b / 2) / 2 for a, b in zip(p, m, strict=True)]
    want = math.sqrt(h(mid) - (h(p) + h(m)) / 2)
    assert abs(q.js_distance(np.array(p), np.array(m))[0] - want) < 1e-12
    assert q.js_distance(np.array(p), np.array(p))[0] == 0 and q.js_distance(np.array([1, 0]), np.array([0, 1]))[0] == 1


def test_a_foreign_histogram_is_rejected(docs):
    rules = q.Rules(q.fit(docs))
    import pyarrow as pa

    text = " ".join("#%d%d@$^~" % (i, i * 7) for i in range(120))
    assert not q.judge(pa.array([text]), ["en"], rules)["kept"][0]
    few = " ".join("#%d" % i for i in range(60))[:190]
    assert not q.judge(pa.array([few]), ["en"], rules)["base_failed"][0] and q.judge(pa.array([few]), ["en"], rules)["kept"][0]


def test_most_labelled_good_documents_stay(spark, docs, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    kept = q.score(docs, q.Rules(q.fit(docs)), ["doc_id"]).join(labels, "doc_id")
    good = kept.where("quality = 1 and not base_failed")
    assert good.where("kept").count() == good.count()


def brute_verdicts(rows, rules=q.Rules()):
    """Distances and verdicts from plain counters, by (language, text)."""
    kind = lambda c: 0 if "a" <= c <= "z" else 1 if "A" <= c <= "Z" else 2 if "0" <= c <= "9" else 3 if c in " \t\n\x0b\x0c\r" else 4 if c in ".,;:!?'\"()-" else 5 if c < "\x80" else 6
    low = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t)
    words_of = lambda t: re.findall("[^\x20\x09-\x0d]+", low(t))

    def distance(p, r):
        if not sum(p.values()) or not sum(r.values()):
            return 0.0
        h = lambda d: -sum(x * math.log2(x) for x in d.values() if x)
        share = lambda d: {k: x / sum(d.values()) for k, x in d.items()}
        p, r = share(p), share(r)
        mid = {k: (p.get(k, 0) + r.get(k, 0)) / 2 for k in {*p, *r}}
        return math.sqrt(max(0.0, h(mid) - (h(p) + h(r)) / 2))

    chars, words = {}, {}
    for lang, t in rows:
        chars.setdefault(lang or "und", Counter()).update(map(kind, t or ""))
        words.setdefault(lang or "und", Counter()).update(words_of(t or ""))
    top = {k: dict(sorted(c.items(), key=lambda x: (-x[1], x[0].encode()))[:100]) for k, c in words.items()}
    fold = lambda c, k: Counter({w: n for w, n in c.items() if w in top[k]}) + Counter({None: sum(n for w, n in c.items() if w not in top[k])})
    out = {}
    for lang, t in rows:
        k, t = lang or "und", t or ""
        c, w = distance(Counter(map(kind, t)), chars[k]), distance(fold(Counter(words_of(t)), k), fold(words[k], k))
        judged = len(words_of(t)) >= 50 and len(t) >= 200
        out[lang, t] = c, w, not brute(t)[5] and not (judged and (c > rules.max_char_distance or w > rules.max_word_distance))
    return out


def test_distances_and_verdicts_match_brute_force(spark, docs, odd):
    """The query itself on the small tables, and rows of languages that only one document has, without a language, and very long."""
    rare = spark.createDataFrame([("x", "zu", "ukuthi abantu bathi " * 40 + "i"), ("y", None, "? ! # " * 90), ("z", "", "la la lo " * 60), ("z", "", "la la lo " * 60), ("long", "en", "the quick brown fox, it is said, jumps.\n" * 60_000)], "doc_id string, lang string, text string")
    for df in (docs, odd.where("text is null or length(text) < 100000"), rare):
        rows = [(r["lang"], r["text"]) for r in df.collect()]
        want = brute_verdicts(rows)
        got = q.score(df, q.Rules(q.fit(df)), ["doc_id", "lang", "text"]).collect()
        assert len(got) == len(rows)
        for r in got:
            c, w, kept = want[r["lang"], r["text"] or ""]
            assert abs(r["char_distance"] - c) < 1e-6 and abs(r["word_distance"] - w) < 1e-6 and r["kept"] == kept


def test_a_document_is_not_judged_by_other_languages(docs):
    import pyarrow as pa

    refs = q.fit(docs)
    text = next(r["text"] for r in docs.collect() if r["lang"] == "de" and not brute(r["text"])[5] and brute(r["text"])[0] > 300)
    judge = lambda lang, known: q.judge(pa.array([text]), [lang], q.Rules(known))
    alone = {k: refs[k] for k in ("en",)}
    assert judge("en", refs)["word_distance"][0] == judge("en", alone)["word_distance"][0] > judge("de", refs)["word_distance"][0]
    assert judge("xx", refs)["word_distance"][0] == 0 and judge("xx", refs)["kept"][0]


def test_characters_are_counted_in_little_memory():
    import tracemalloc

    import pyarrow as pa

    texts = pa.array(["x" * 3_000_001 + "É", None, "Ab 1,#" * 300_000, ""])
    tracemalloc.start()
    got = q._char_counts(texts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got.tolist() == [[3_000_001, 0, 0, 0, 0, 0, 1], [0] * 7, [300_000] * 6 + [0], [0] * 7]
    assert peak < 8 << 20

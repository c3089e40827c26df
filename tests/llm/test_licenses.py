import math
import random
import re
from collections import Counter

import pytest

from recordlink.llm import licenses as lic


def brute_base(text):
    low = re.sub(r"[A-Z]", lambda m: m[0].lower(), text or "")
    words = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", low)
    at = [(i, label) for i in range(len(words)) for p, label in lic.BASE.items() if words[i : i + len(p.split())] == p.split()]
    places = [i for i, _ in at]
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted({x for _, x in at}))


COLS = ["n_words", "n_base", "first_word", "last_word", "base_labels"]


def test_base(docs, odd, none):
    for df in (docs, odd):
        rows = lic.scan(df, keep=("doc_id", "text")).collect()
        assert len(rows) == df.count()
        for r in rows:
            assert tuple(r[c] for c in COLS) == brute_base(r["text"])
            assert set(filter(None, r["base_labels"].split(","))) <= set(filter(None, r["labels"].split(",")))
            assert 0 <= r["score"] <= 1
    assert lic.scan(none).count() == 0


INDEX = lic.build({"": 1000})


def test_overlapping_base_phrases():
    text = b"MIT license-mit License, apache_license! the General Public\nLicense permit license"
    row = lic.scan_text(text, INDEX)
    assert row[:5] == brute_base(text.decode())
    assert row[1] == 4 and row[4] == "apache,gpl,mit"


def test_each_template_is_found_whole_and_slightly_changed():
    for label, passage, _ in lic.TEMPLATES:
        noise = " ".join(f"w{i}" for i in range(300))
        text = f"{noise} # {passage.upper()} {noise}"
        row = lic.scan_text(text.encode(), INDEX)
        assert label in row[5].split(","), label
        assert abs(row[7] - 300) <= 2 and row[6] >= 0.6


def test_scattered_words_are_no_licence():
    for _, passage, _ in lic.TEMPLATES:
        words = sorted(passage.split())
        assert lic.scan_text(" ".join(words).encode(), INDEX)[5] == lic.scan_text(" ".join(words).encode(), INDEX)[4]


COMMON = {"the", "of", "to", "and", "or", "in", "is", "a", "this", "you", "it", "for", "with", "on", "at", "by"}


def brute_labels(text, counts, rare=16, min_share=0.6):
    """Every template against every shift, word by word."""
    words = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    idf = lambda w: math.log((counts.get("", 0) + 1) / (counts.get(w, 0) + 1)) + 1
    labels, best = set(), 0.0
    for label, passage, phrases in lic.TEMPLATES:
        own = passage.split()
        top = set(sorted(set(own), key=lambda w: (-idf(w), w.encode()))[:rare])
        places = [(i, w) for i, w in enumerate(own) if w in top]
        full, shares = sum(idf(w) for _, w in places), []
        for shift in range(-len(own) - 2, len(words) + 3):
            got = sum(idf(w) for i, w in places if any(0 <= shift + i + d < len(words) and words[shift + i + d] == w for d in (-2, -1, 0, 1, 2)))
            near = " " + " ".join(words[max(0, shift - 8) : max(0, shift + len(own) + 8)]) + " "
            if got >= min_share * full - 1e-9 and all(f" {p} " in near for p in phrases):
                shares.append(got / full)
        if shares:
            labels.add(label)
            best = max(best, max(shares))
    return labels, min(1.0, best)


def counts_of(texts):
    known = {w for _, passage, _ in lic.TEMPLATES for w in passage.split()}
    seen = Counter(w for t in texts for w in known & {x.decode() for x in lic.words_of((t or "").encode())})
    return seen | {"": len(texts)}


def damaged(rng, words, edits):
    words = list(words)
    for _ in range(edits):
        at, kind = rng.randrange(len(words)), rng.randrange(3)
        words[at : at + (kind != 1)] = [] if kind == 0 else ["zz"]
    return words


def test_labels_and_scores_match_brute_force(spark):
    """Whole, damaged, cut, shuffled, repeated and mixed passages among noise."""
    rng, texts = random.Random(5), []
    for n in range(60):
        parts = []
        for _ in range(rng.randrange(1, 4)):
            own = rng.choice(lic.TEMPLATES)[1].split()
            if n % 5 == 4:
                rng.shuffle(own)
            lo = rng.randrange(len(own)) if n % 3 == 2 else 0
            parts += damaged(rng, own[lo:], rng.randrange(0, 12)) + [f"w{rng.randrange(50)}" for _ in range(rng.randrange(0, 30))]
        texts.append(rng.choice([" ", "\n# ", ", "]).join(parts))
    texts += ["", None, "the of and " * 400, texts[0], "é " + texts[1].upper()]
    rows = lic.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    counts, found = counts_of(texts), 0
    for r in rows:
        want, share = brute_labels(texts[r["doc_id"]], counts)
        assert set(filter(None, r["labels"].split(","))) == want | set(filter(None, r["base_labels"].split(",")))
        assert r["base_labels"] or abs(r["score"] - share) < 1e-9
        found += bool(want)
    assert 15 < found < len(texts) - 3


def test_documents_match_brute_force(docs):
    rows = lic.scan(docs, keep=("doc_id", "text")).collect()
    counts = counts_of([r["text"] for r in rows])
    few = [r for r in rows if r["labels"]] + [r for r in rows if len(r["text"]) < 900][:25]
    for r in few:
        if len(r["text"]) < 6000:
            assert set(filter(None, r["labels"].split(","))) - set(filter(None, r["base_labels"].split(","))) <= brute_labels(r["text"], counts)[0] <= set(r["labels"].split(","))


def test_a_damaged_passage_before_an_intact_one():
    label, passage, phrases = next(t for t in lic.TEMPLATES if t[0] == "isc")
    damaged_first = passage.replace("with or without fee is hereby granted", "with or without fee was granted").split()
    text = " ".join(damaged_first) + " x " * 60 + passage.replace("appear", "seem").replace("copies", "texts")
    assert "isc" in lic.scan_text(text.encode(), INDEX)[5].split(",")


def test_a_licence_of_many_files_keeps_its_label():
    """Each licence in a quarter or nearly all of the files, function words in nearly all; the file's neighbours do not matter."""
    for share in (250, 999):
        for label, passage, _ in lic.TEMPLATES:
            index = lic.build({"": 1000} | {w: 900 for w in COMMON} | {w: share for w in passage.split()})
            assert label in {m[0] for m in lic.matches(passage.encode().split(), index)}


def test_all_licences_of_one_file_are_found():
    index = lic.build({"": 1000} | {w: 900 for w in COMMON})
    text = " x y z ".join(passage for _, passage, _ in lic.TEMPLATES)
    assert {m[3] for m in lic.matches(text.encode().split(), index)} == set(range(len(lic.TEMPLATES)))


def test_templates_of_the_callers_own(spark):
    own = [("own", "You may share this text with friends, provided that they ask.", ["share this text"]), ("bare", "all rights kept by the house", None)]
    df = spark.createDataFrame([("a", "x You may share THIS text with friends provided that they ask y", 1), ("b", "all rights kept by the house", 2), ("c", None, 3)], "doc_id string, text string, labels int")
    got = {r["doc_id"]: (r["labels"], r["labels_in"]) for r in lic.scan(df, keep=("doc_id", "labels"), templates=own).collect()}
    assert got == {"a": ("own", 1), "b": ("bare", 2), "c": ("", 3)}
    with pytest.raises(ValueError):
        lic.templates_of([("x", " ", None)])


def test_a_very_long_file():
    text = ("lorem the of and software " * 400_000).encode() + lic.TEMPLATES[0][1].encode()
    assert "mit" in lic.scan_text(text, INDEX)[5].split(",")

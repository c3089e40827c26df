"""Quality rules: plain counts, then the distance of a document's histograms from language references.

References are learnt from the corpus: for each language the histogram of character classes and of its
``top_words`` most frequent words (all others together count as one).  A document is compared by Jensen-Shannon distance
(square root of the divergence in bits, 0 to 1) with its own language's reference, and with no other; a language that the references
do not know is not judged by them.  Short documents are not judged by histograms either,
which are too noisy there: ``min_chars`` and ``min_words`` guard them.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

SYMBOLS = b"#*$%&|<>"
#: Character classes: small and capital ASCII letters, digits, blanks, sentence marks, other ASCII, all beyond ASCII.
CLASSES = 7
#: Bytes of text whose words are counted together in a task.
FIT_CHUNK = 10 << 20
#: Bytes of a text whose characters are counted at once.
COUNT_PIECE = 1 << 18
#: Hash groups of words in which the most frequent are ranked, step by step.
RANK_GROUPS = (1024, 32, 1)


def class_table() -> np.ndarray:
    """The class of each byte; bytes inside a code point get none (255)."""
    t = np.full(256, 5, np.uint8)
    t[ord("a") : ord("z") + 1], t[ord("A") : ord("Z") + 1], t[ord("0") : ord("9") + 1] = 0, 1, 2
    t[[9, 10, 11, 12, 13, 32]] = 3
    t[np.frombuffer(b".,;:!?'\"()-", np.uint8)] = 4
    t[0x80:0xC0], t[0xC0:] = 255, 6
    return t


CLASS_OF = class_table()


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distances between rows of p and q (counts or shares; an empty row is at distance 0)."""
    p, q = np.atleast_2d(np.asarray(p, float)), np.atleast_2d(np.asarray(q, float))
    sp, sq = p.sum(1, keepdims=True), q.sum(1, keepdims=True)
    p, q = p / np.where(sp, sp, 1), q / np.where(sq, sq, 1)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        kl = np.where(p > 0, p * np.log2(p / m), 0).sum(1) + np.where(q > 0, q * np.log2(q / m), 0).sum(1)
    return np.where((sp[:, 0] > 0) & (sq[:, 0] > 0), np.sqrt(np.clip(kl / 2, 0, 1)), 0.0)


@dataclass
class Reference:
    """What one language looks like."""

    chars: np.ndarray
    words: dict[bytes, int]
    word_counts: np.ndarray  # of ``words`` in order, then of all other words


@dataclass
class Rules:
    """Thresholds; ``references`` by language."""

    references: dict[str, Reference] = field(default_factory=dict)
    max_char_distance: float = 0.30
    max_word_distance: float = 0.50
    min_chars: int = 200
    min_words: int = 50
    max_repeat_percent: int = 50


def _char_counts(column: pa.Array) -> np.ndarray:
    """Code points of each class in each text; a text is counted in pieces, as counting takes eight bytes and more for each of its."""
    raw = common.texts(column)
    ends = np.frombuffer(raw.buffers()[1], np.int64)[raw.offset : raw.offset + len(raw) + 1]
    data = np.frombuffer(raw.buffers()[2] or b"", np.uint8)
    seen = np.zeros((len(raw), 256), np.int64)
    for own, lo, hi in zip(seen, ends.tolist(), ends[1:].tolist(), strict=False):
        for at in range(lo, hi, COUNT_PIECE):
            own += np.bincount(data[at : min(hi, at + COUNT_PIECE)], minlength=256)
    return seen @ (CLASS_OF[:, None] == np.arange(CLASSES)).astype(np.int64)


def fit(df: DataFrame, top_words: int = 100, max_languages: int = 1000, text_col: str = "text", lang_col: str = "lang") -> dict[str, Reference]:
    """The reference of each language, over all rows of it.

    Only ``top_words`` words and seven classes a language come to the driver; more than ``max_languages`` languages are
    an error rather than a silent cut.  A null language counts as "und"; of equally frequent words the first in byte order counts;
    repeated rows count each; an empty table has no references.
    """
    src = df.select(F.coalesce(F.nullif(F.col(lang_col).cast("string"), F.lit("")), F.lit("und")).alias("lang"), F.col(text_col).cast("string").alias("text"))

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        langs = np.array(part.column(0).to_pylist(), object)
        chars, t = _char_counts(part.column(1)), common.tokenize(part.column(1))
        owner, rows = t.owner(), []
        for lang in sorted(set(langs)):
            own = langs == lang
            n = np.bincount(t.codes[own[owner]], minlength=len(t.words))
            seen = np.flatnonzero(n)
            words = pa.concat_arrays([t.words.take(pa.array(seen)).cast(pa.string()), pa.array([str(i) for i in range(CLASSES + 2)], pa.string())])
            kinds = np.concatenate([np.zeros(len(seen), np.int32), np.ones(CLASSES + 2, np.int32)])
            counts = np.concatenate([n[seen], chars[own].sum(0), [own.sum(), n.sum()]])
            rows.append(pa.RecordBatch.from_arrays([pa.array([lang] * len(words), pa.string()), pa.array(kinds), words, pa.array(counts, pa.int64())], names=["lang", "kind", "word", "n"]))
        return pa.Table.from_batches(rows).combine_chunks().to_batches()[0]

    made = common.map_arrow(src, run, "lang string, kind int, word string, n long", limit=FIT_CHUNK)
    counts = made.groupBy("lang", "kind", "word").agg(F.sum("n").alias("n"))
    # The most frequent of many hash groups first, then of fewer: no task ranks a language's whole vocabulary.
    top, most = counts, max(top_words, CLASSES + 2)
    for groups in RANK_GROUPS:
        w = Window.partitionBy("lang", "kind", F.pmod(F.xxhash64("word"), F.lit(groups))).orderBy(F.desc("n"), "word")
        top = top.withColumn("r", F.row_number().over(w)).where(F.col("r") <= most).drop("r")
    top = common.settle(top)
    enough = (F.col("kind") == 1) & (F.col("word") == str(CLASSES)) & (F.col("n") > 0)
    known = sorted(r["lang"] for r in top.where(enough).select("lang").limit(max_languages + 1).collect())
    if len(known) > max_languages:
        raise ValueError(f"more than {max_languages} languages: the references would not stay small")
    got: dict[str, list] = {x: [np.zeros(CLASSES), [], 0.0] for x in known}
    for r in top.where(F.col("lang").isin(known)).collect() if known else []:
        if r["kind"] == 0:
            got[r["lang"]][1].append((-r["n"], r["word"].encode()))
        elif int(r["word"]) < CLASSES:
            got[r["lang"]][0][int(r["word"])] = r["n"]
        elif int(r["word"]) == CLASSES + 1:
            got[r["lang"]][2] = float(r["n"])
    out = {}
    for lang, (chars, ranked, total) in got.items():
        best = sorted(ranked)[:top_words]
        counted = np.array([-n for n, _ in best], float)
        out[lang] = Reference(chars, {w: i for i, (_, w) in enumerate(best)}, np.append(counted, total - counted.sum()))
    return out


def repeat_words(words: list) -> int:
    """Words that stand in a three-word window found twice or more."""
    windows = list(zip(words, words[1:], words[2:], strict=False))
    if len(set(windows)) == len(windows):
        return 0
    often = Counter(windows)
    hit = np.fromiter((often[w] > 1 for w in windows), bool, len(windows))
    cover = np.zeros(len(words), bool)
    for shift in range(3):
        cover[shift : shift + len(windows)] |= hit
    return int(cover.sum())


def dup_lines(text: bytes) -> int:
    """Lines with a word that equal an earlier line."""
    lines = [x for x in text.split(b"\n") if x.strip()]
    return len(lines) - len(set(lines))


def _ascii_symbols(column: pa.Array) -> np.ndarray:
    raw = common.text_bytes(column)
    gone = bytes(b for b in range(256) if b not in SYMBOLS)
    return np.array([len(x.translate(None, gone)) for x in raw], np.int64)


def judge(column: pa.Array, langs: list[str | None], rules: Rules) -> dict[str, np.ndarray]:
    """Counts, distances and verdicts of texts."""
    t = common.tokenize(column, lower=False)
    raw = common.text_bytes(column)
    chars = _char_counts(column)
    n_words = t.lengths
    out = {
        "n_words": n_words,
        "word_chars": chars.sum(1) - chars[:, 3],
        "n_symbols": _ascii_symbols(column),
        "n_dup_lines": np.array([dup_lines(x) for x in raw], np.int64),
        "n_repeat_words": np.array([repeat_words(t.codes[a:b].tolist()) for a, b in zip(t.offsets, t.offsets[1:], strict=False)], np.int64),
    }
    out["base_failed"] = (n_words < rules.min_words) | (100 * out["n_repeat_words"] > rules.max_repeat_percent * n_words)
    refs = rules.references
    n = len(raw)
    char_d, word_d = np.zeros(n), np.zeros(n)
    if refs:
        words = [w.lower() for w in t.words.cast(pa.large_binary()).to_pylist()]
        index = {k: np.array([r.words.get(w, len(r.words)) for w in words], np.int64) for k, r in refs.items()}

        def distance(i: int, k: str) -> tuple[float, float]:
            r = refs[k]
            own = np.bincount(index[k][t.codes[t.offsets[i] : t.offsets[i + 1]]], minlength=len(r.words) + 1)
            return float(js_distance(chars[i], r.chars)[0]), float(js_distance(own, r.word_counts)[0])

        for i in range(n):
            if (k := langs[i] or "und") in refs:
                char_d[i], word_d[i] = distance(i, k)
    judged = (n_words >= rules.min_words) & (chars.sum(1) >= rules.min_chars)
    far = judged & ((char_d > rules.max_char_distance) | (word_d > rules.max_word_distance))
    return out | {"char_distance": char_d, "word_distance": word_d, "kept": ~out["base_failed"] & ~far}


OUT = {"n_words": "long", "word_chars": "long", "n_symbols": "long", "n_dup_lines": "long", "n_repeat_words": "long", "base_failed": "boolean", "char_distance": "double", "word_distance": "double", "kept": "boolean"}


def score(df: DataFrame, rules: Rules, keep: list[str], text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """``keep`` beside the columns of OUT for every row.

    A null or empty text has no words and so fails; a null or empty language is "und"; texts of any length are read whole; a
    distance equal to its threshold passes; repeated rows get equal results; an empty table gives no rows; kept columns come back
    under free names.
    """
    from pyspark.sql import types as T

    names = common.free_names(keep, OUT)
    src = df.select(*[F.col(f"`{c}`").alias(f"k{i}") for i, (c, _) in enumerate(names)], F.col(f"`{lang_col}`").cast("string").alias("lang"), F.col(f"`{text_col}`").cast("string").alias("text"))
    schema = T.StructType([*(T.StructField(new, df.schema[old].dataType) for old, new in names), *T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in OUT.items())).fields])
    n = len(names)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        got = judge(part.column(n + 1), part.column(n).to_pylist(), rules)
        return pa.RecordBatch.from_arrays([*part.columns[:n], *(pa.array(got[k]) for k in OUT)], names=schema.names)

    return common.map_arrow(src, run, schema)


def keep_good(df: DataFrame, rules: Rules, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The rows of df that the rules keep, with all their columns."""
    names = df.columns
    ti, li = names.index(text_col), names.index(lang_col)

    def run(batches):
        for batch in batches:
            for part in common.chunks(batch, text_col):
                ok = judge(part.column(ti), part.column(li).to_pylist(), rules)["kept"]
                if ok.any():
                    yield part.filter(pa.array(ok))
        common.release()

    return df.mapInArrow(run, df.schema)

"""Sentences as vectors: hashed character n-grams, TF-IDF, a pre-trained model, a fine-tuned head."""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.vectors import matrix, unit, vectors_of
from ..sources.shared import settle

VECTOR = T.ArrayType(T.FloatType(), False)


def grams_of_words(text: Column, ns: tuple[int, ...]) -> Column:
    """The character n-grams of each blank-separated word, padded by # on both sides (a shorter word gives itself)."""
    words = F.filter(F.split(F.lower(text), " +"), lambda w: w != "")

    def of(w: Column) -> Column:
        p = F.concat(F.lit("#"), w, F.lit("#"))

        def grams(n: int) -> Column:
            return F.transform(F.sequence(F.lit(1), F.greatest(F.char_length(p) - n + 1, F.lit(1))), lambda i: F.substring(p, i, F.lit(n)))

        return F.concat(*[grams(n) for n in ns])

    return F.flatten(F.transform(words, of))


def gram_list(text: str, ns: tuple[int, ...]) -> list[str]:
    out = []
    for w in text.lower().split(" "):
        if w:
            p = f"#{w}#"
            for n in ns:
                out += [p[i : i + n] for i in range(max(len(p) - n + 1, 1))]
    return out


@dataclass(frozen=True)
class HashedNgramEncoder:
    """A stand-in for a language model where none can be had: signed counts of hashed character n-grams.

    Letter case does not matter.  Bucket and sign come from the gram's md5, so SQL engines agree.
    """

    dim: int = 768
    ns: tuple[int, ...] = (3, 4)
    signed: bool = True

    def sparse(self, df: DataFrame, id_col: str, text: str = "sentence") -> DataFrame:
        """(id, bucket, weight): integers, zeros left out.  Built-in functions only."""
        gram = df.select(F.col(id_col), F.explode(grams_of_words(F.coalesce(F.col(text), F.lit("")), self.ns)).alias("gram"))
        h = F.md5(F.encode("gram", "UTF-8"))
        bucket = F.pmod(F.conv(F.substring(h, 1, 6), 16, 10).cast("long"), F.lit(self.dim)).cast("int")
        sign = F.when(F.conv(F.substring(h, 7, 1), 16, 10).cast("int") % 2 == 0, 1).otherwise(-1) if self.signed else F.lit(1)
        counted = gram.groupBy(id_col, bucket.alias("bucket")).agg(F.sum(sign).cast("int").alias("weight"))
        return counted.where("weight != 0")

    def word(self, w: str) -> tuple[np.ndarray, np.ndarray]:
        """Buckets and signs of one word's grams."""
        hashes = [hashlib.md5(g.encode()).hexdigest() for g in gram_list(w, self.ns)]
        return np.array([int(h[:6], 16) % self.dim for h in hashes], np.int64), np.array([1.0 if not self.signed or int(h[6], 16) % 2 == 0 else -1.0 for h in hashes])

    def block(self, texts: list[str | None], known: dict | None = None) -> np.ndarray:
        """Texts as rows; a word is hashed once, and ``known`` remembers it for further blocks."""
        known = {} if known is None else known
        if len(known) > 100_000:
            known.clear()
        made, owner = [], []
        for i, t in enumerate(texts):
            for w in (t or "").lower().split(" "):
                if w:
                    got = known.get(w)
                    if got is None:
                        got = known[w] = self.word(w)
                    made.append(got)
                    owner.append(i)
        if not made:
            return np.zeros((len(texts), self.dim))
        rows = np.repeat(np.array(owner), [len(a) for a, _ in made])
        at = rows * self.dim + np.concatenate([a for a, _ in made])
        return np.bincount(at, np.concatenate([s for _, s in made]), len(texts) * self.dim).reshape(len(texts), self.dim)

    def encode(self, df: DataFrame, id_col: str, text: str = "sentence", out: str = "vec") -> DataFrame:
        """(id, vec): the same counts, dense, in Arrow batches; whole numbers, so that cosines agree with the sparse form."""
        return encode_blocks(df, id_col, text, out, self.block, {})


def encode_blocks(df: DataFrame, id_col: str, text: str, out: str, block, *state) -> DataFrame:
    """Apply ``block(list of texts, *state) -> matrix`` to Arrow batches; each task has a copy of ``state`` of its own."""
    schema = T.StructType([df.schema[id_col], T.StructField(out, VECTOR)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 2048):  # a Python task's memory cannot spill
                part = whole.slice(lo, 2048)
                yield pa.RecordBatch.from_arrays([part.column(0), vectors_of(block(part.column(1).to_pylist(), *state))], names=[id_col, out])

    return df.select(id_col, text).mapInArrow(run, schema)


class TfidfEncoder:
    """Bag of words (or of character n-grams): term counts times inverse document frequency, unit length."""

    def __init__(self, tokenizer: str = "word", ns: tuple[int, ...] = (3, 4), smooth: bool = True, vocab_size: int | None = None, hash_dim: int = 4096) -> None:
        """``vocab_size``: only the terms of most reference rows (ties by name); ``hash_dim``: the dense form's dimensions."""
        if tokenizer not in ("word", "char"):
            raise ValueError("tokenizer is word or char")
        self.tokenizer, self.ns, self.smooth, self.vocab_size, self.hash_dim = tokenizer, ns, smooth, vocab_size, hash_dim
        self.idf: DataFrame | None = None

    def terms(self, df: DataFrame, id_col: str, text: str = "sentence") -> DataFrame:
        t = F.coalesce(F.col(text), F.lit(""))
        each = F.filter(F.split(F.lower(t), "[^a-z0-9]+"), lambda w: w != "") if self.tokenizer == "word" else grams_of_words(t, self.ns)
        return df.select(id_col, F.explode(each).alias("term")).groupBy(id_col, "term").agg(F.count("*").alias("tf"))

    def fit(self, df: DataFrame, id_col: str, text: str = "sentence") -> TfidfEncoder:
        """Document frequencies of the reference's terms; a table, since the vocabulary grows with the data."""
        n = df.agg(F.count("*").alias("n"))
        counts = self.terms(df, id_col, text).groupBy("term").agg(F.count("*").alias("df"))
        plus = 1 if self.smooth else 0
        idf = counts.join(F.broadcast(n)).select("term", "df", (F.log((F.col("n") + plus) / (F.col("df") + plus)) + 1).alias("idf"))
        if self.vocab_size is not None:
            idf = idf.orderBy(F.desc("df"), "term").limit(self.vocab_size)
        self.idf = settle(idf.select("term", "idf"))
        return self

    def sparse(self, df: DataFrame, id_col: str, text: str = "sentence") -> DataFrame:
        """(id, term, w); terms outside the reference's vocabulary drop out."""
        if self.idf is None:
            raise ValueError("fit first")
        raw = self.terms(df, id_col, text).join(self.idf, "term").withColumn("w", F.col("tf") * F.col("idf"))
        norm = raw.groupBy(id_col).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
        return raw.join(norm, id_col).select(id_col, "term", (F.col("w") / F.col("norm")).alias("w"))

    def hashed(self, df: DataFrame, id_col: str, dim: int | None = None, text: str = "sentence") -> DataFrame:
        """(id, vec): the sparse form in a hashed term space, for gatherers of dense vectors."""
        dim = dim or self.hash_dim
        s = self.sparse(df, id_col, text).select(id_col, F.pmod(F.xxhash64("term"), F.lit(dim)).cast("int").alias("b"), "w")
        s = s.groupBy(id_col, "b").agg(F.sum("w").alias("w")).groupBy(id_col).agg(F.map_from_entries(F.collect_list(F.struct("b", "w"))).alias("m"))
        every = df.select(id_col).join(s, id_col, "left")
        vec = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0)).cast("float"))
        return every.select(id_col, vec.alias("vec"))

    def encode(self, df: DataFrame, id_col: str, text: str = "sentence", out: str = "vec") -> DataFrame:
        return self.hashed(df, id_col, text=text).withColumnRenamed("vec", out)


class PretrainedEncoder:
    """A frozen transformer in ONNX form with its tokenizer file, mean-pooled over tokens, cut at ``max_tokens``.

    ``model`` and ``tokenizer`` are names of files given to ``SparkContext.addFile``, or paths that every executor has.
    ``session`` may be a picklable factory of an object with ``run(texts) -> matrix``, for other runtimes.
    """

    def __init__(self, model: str = "", tokenizer: str = "", dim: int = 768, max_tokens: int = 128, session=None) -> None:
        self.model, self.tokenizer, self.dim, self.max_tokens, self.session = model, tokenizer, dim, max_tokens, session

    def encode(self, df: DataFrame, id_col: str, text: str = "sentence", out: str = "vec") -> DataFrame:
        spec = self
        state: dict[str, object] = {}  # one model for each worker process

        def block(texts: list[str | None]) -> np.ndarray:
            if "run" not in state:
                state["run"] = spec.session() if spec.session else OnnxSession(spec.model, spec.tokenizer, spec.max_tokens)
            made = np.asarray(state["run"].run([t or "" for t in texts]))
            if made.shape != (len(texts), spec.dim):
                raise ValueError(f"the model gives {made.shape}, not {(len(texts), spec.dim)}")
            return unit(made)

        return encode_blocks(df, id_col, text, out, block)


class OnnxSession:
    def __init__(self, model: str, tokenizer: str, max_tokens: int) -> None:
        import os

        import onnxruntime
        from pyspark import SparkFiles
        from tokenizers import Tokenizer

        at = lambda p: p if os.path.exists(p) else SparkFiles.get(p)
        self.model = onnxruntime.InferenceSession(at(model))
        self.tokenizer = Tokenizer.from_file(at(tokenizer))
        self.tokenizer.enable_truncation(max_tokens)
        self.tokenizer.enable_padding()

    def run(self, texts: list[str]) -> np.ndarray:
        got = self.tokenizer.encode_batch(texts)
        ids, mask = np.array([e.ids for e in got]), np.array([e.attention_mask for e in got])
        wanted = {i.name for i in self.model.get_inputs()}
        hidden = self.model.run(None, {k: v for k, v in {"input_ids": ids, "attention_mask": mask}.items() if k in wanted})[0]
        return (hidden * mask[:, :, None]).sum(1) / np.maximum(mask.sum(1), 1)[:, None]


class ProjectedEncoder:
    """A base encoder followed by a learnt square matrix; at the identity it is the base encoder."""

    def __init__(self, base, w: np.ndarray) -> None:
        self.base, self.w = base, np.asarray(w, np.float64)

    def encode(self, df: DataFrame, id_col: str, text: str = "sentence", out: str = "vec") -> DataFrame:
        return project(self.base.encode(df, id_col, text, out), id_col, self.w, out)

    def save(self, spark, path: str) -> None:
        rows = [(i, row.tolist()) for i, row in enumerate(self.w)]
        spark.createDataFrame(rows, "i int, row array<double>").write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark, path: str, base) -> ProjectedEncoder:
        rows = spark.read.parquet(path).orderBy("i").collect()  # as many rows as dimensions
        return cls(base, np.array([r["row"] for r in rows]))


def project(vectors: DataFrame, id_col: str, w: np.ndarray, out: str = "vec") -> DataFrame:
    """Unit vectors times w, at unit length."""
    shared = vectors.sparkSession.sparkContext.broadcast(w)  # dim x dim numbers, whatever the data's size
    schema = T.StructType([vectors.schema[id_col], T.StructField(out, VECTOR)])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            made = unit(matrix(f[out]) @ shared.value.T) if len(f) else np.zeros((0, 0))
            yield pd.DataFrame({id_col: f[id_col], out: list(made.astype(np.float32))})

    return vectors.select(id_col, out).mapInPandas(run, schema)


def save_index(vectors: DataFrame, path: str, cell: str | None = None, codec: str = "zstd") -> None:
    """Encode once: vectors as Parquet, a folder for each cell if there is one."""
    w = vectors.write.mode("overwrite").option("compression", codec)
    (w.partitionBy(cell) if cell else w).parquet(path)


def quantize_int8(vectors: DataFrame, id_col: str, vec: str = "vec") -> DataFrame:
    """(id, code, scale): 8-bit numbers, vec ~ code * scale / 127; a quarter of the room."""
    top = F.array_max(F.transform(vec, lambda x: F.abs(x)))
    scale = F.when(top > 0, top).otherwise(1.0)
    return vectors.select(id_col, F.transform(vec, lambda x: F.round(x / scale * 127).cast("tinyint")).alias("code"), scale.cast("float").alias("scale"))


def describe(encoder) -> str:
    """A label for result tables; the hashed encoder says that it stands in for a model."""
    if isinstance(encoder, HashedNgramEncoder):
        return f"stand-in hashed-{encoder.dim}"
    if isinstance(encoder, ProjectedEncoder):
        return describe(encoder.base) + " fine-tuned"
    if isinstance(encoder, TfidfEncoder):
        return f"tfidf-{encoder.tokenizer}"
    return json.dumps(type(encoder).__name__).strip('"')

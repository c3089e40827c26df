"""BPE with word ends: encode by a priority queue of merge ranks, decode by vocabulary strings.

The symbols of a word form a doubly linked list.  A heap holds (rank, position) of each adjacent
pair that can merge; a popped entry whose pair has changed since is stale and skipped.  A word is
encoded once per worker and remembered, since texts repeat words.

Normalising (NFC, lower case) and splitting act within runs of non-blanks, so each
blank-separated run of a text is encoded by itself and the text's ids are theirs in a row.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from array import array
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import common

#: Runs of non-blanks that a worker remembers at most (twice as many live while a generation is replaced), and pieces: the same
#: word in other letter case or with other marks around it is merged once.
CACHE_WORDS = 100_000
CACHE_PIECES = 250_000
#: Longer runs and pieces are not remembered, which bounds the caches' bytes too.
CACHE_BYTES = 64


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte: itself where printable, else the next free code point from 256."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    kept = set(own)
    return [chr(b) if b in kept else chr(next(spare)) for b in range(256)]


class WordBpe:
    """A tokenizer read from a ``tokenizers`` JSON file of the word-end kind, without a network or training."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if model["type"] != "BPE" or spec.get("decoder") is not None or spec.get("post_processor") is not None:
            raise ValueError(f"{path}: not a BPE file with word ends and no decoder")
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model["end_of_word_suffix"] or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.strings = {i: s for s, i in self.vocab.items()} | {i: s for s, i in self.special.items()}
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ", 1)
            self.merges.setdefault((self.vocab[a], self.vocab[b]), (rank, self.vocab[a + b]))
        symbols = byte_symbols()
        self.inner = [self.vocab[s] for s in symbols]
        self.final = [self.vocab[s + self.suffix] for s in symbols]
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.piece = regex.compile(split["pattern"]["Regex"], regex.V0)
        self.pieces: dict[str, array] = {}
        self.young: dict[bytes, tuple[bytes, bytes]] = {}
        self.old: dict[bytes, tuple[bytes, bytes]] = {}

    def shrink(self) -> None:
        """Forget all but the first pieces seen, which are the frequent ones: the worker may do other work next."""
        self.young, self.old = {}, {}
        self.pieces = dict(islice(self.pieces.items(), CACHE_PIECES // 5))

    def merge(self, piece: bytes) -> list[int]:
        """The ids of one pre-token."""
        n = len(piece)
        ids = [self.inner[b] for b in piece]
        ids[-1] = self.final[piece[-1]]
        if n == 1:
            return ids
        merges = self.merges
        after, before = [*range(1, n), -1], [*range(-1, n - 1)]
        heap = []
        for i in range(n - 1):
            if (m := merges.get((ids[i], ids[i + 1]))) is not None:
                heap.append((m[0], i, m[1], ids[i], ids[i + 1]))
        heapq.heapify(heap)
        while heap:
            _, i, made, left, right = heapq.heappop(heap)
            j = after[i]
            if ids[i] != left or j < 0 or ids[j] != right:
                continue  # stale: one of the two has been merged since
            ids[i], ids[j] = made, -1
            k = after[i] = after[j]
            if k >= 0:
                before[k] = i
                if (m := merges.get((made, ids[k]))) is not None:
                    heapq.heappush(heap, (m[0], i, m[1], made, ids[k]))
            h = before[i]
            if h >= 0 and (m := merges.get((ids[h], made))) is not None:
                heapq.heappush(heap, (m[0], h, m[1], ids[h], made))
        return [x for x in ids if x >= 0]

    def run_ids(self, run: str) -> list[int]:
        """The ids of a run of non-blanks: special strings first, then pieces of what lies between."""
        out: list[int] = []
        for part in self.cut.split(run) if self.cut else [run]:
            if part in self.special:
                out.append(self.special[part])
            elif part:
                plain = part if part.isascii() else unicodedata.normalize("NFC", part).replace("Σ", "σ")
                for piece in self.piece.findall(plain.lower()):
                    ids = self.pieces.get(piece)
                    if ids is None:
                        if len(self.pieces) >= CACHE_PIECES:
                            self.pieces.clear()
                        raw = piece.encode()
                        ids = array("I", self.merge(raw))
                        if len(raw) <= CACHE_BYTES:
                            self.pieces[piece] = ids
                    out.extend(ids)
        return out

    def encoded(self, run: bytes) -> tuple[bytes, bytes]:
        """A run's ids as little-endian 32-bit integers, and its decoded text; remembered for a while."""
        got = self.young.get(run)
        if got is None:
            got = self.old.get(run)
            if got is None:
                ids = self.run_ids(run.decode())
                got = np.array(ids, "<u4").tobytes(), self.decode(ids).encode()
            if len(run) > CACHE_BYTES:
                return got
            if len(self.young) >= CACHE_WORDS:
                self.old, self.young = self.young, {}
            self.young[run] = got
        return got

    def decode(self, ids: list[int]) -> str:
        """The vocabulary's strings with a blank between, as a tokenizer without a decoder gives them."""
        return " ".join([self.strings[i] for i in ids])

    def encode(self, text: str | None) -> list[int]:
        return np.frombuffer(b"".join(self.encoded(w)[0] for w in (text or "").encode().split()), "<u4").tolist()

    def encode_column(self, column: pa.Array) -> tuple[list[bytes], list[bytes]]:
        """For each text, its ids as bytes and its decoded text."""
        t = common.tokenize(column, lower=False)
        each = [self.encoded(w) for w in t.words.cast(pa.large_binary()).to_pylist()]
        ids, plain = [e[0] for e in each], [e[1] for e in each]
        # A run of blanks outside ASCII has no ids; it must not add a separator to the decoded text.
        void = np.array([not x for x in ids], bool)
        packed, decoded = [], []
        for lo, hi in zip(t.offsets, t.offsets[1:], strict=False):
            codes = t.codes[lo:hi]
            if len(void) and void[codes].any():
                codes = codes[~void[codes]]
            codes = codes.tolist()
            packed.append(b"".join([ids[c] for c in codes]))
            decoded.append(b" ".join([plain[c] for c in codes]))
        return packed, decoded


@lru_cache(maxsize=4)
def load(path: str) -> WordBpe:
    """One tokenizer for each worker process."""
    return WordBpe(path)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode_documents(df: DataFrame, path: str | None = None, id_cols: tuple[str, ...] = ("doc_id",), text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """``id_cols``, ``token_ids`` array<int> (if ``with_ids``), ``n_tokens``, ``ids_sha256`` and ``decoded_sha256`` of every whole text.

    ``path`` is the vocabulary file as the executors see it; None finds the installed one there.  A null text is empty
    (no ids, digests of nothing); repeated rows give repeated results; texts of any length are encoded whole; of equal merge ranks
    the leftmost pair goes first; an empty table gives no rows; kept columns come back under free names, others are not read.
    """
    out = ({"token_ids": "array<int>"} if with_ids else {}) | {"n_tokens": "long", "ids_sha256": "string", "decoded_sha256": "string"}

    def run(column: pa.Array) -> dict[str, pa.Array]:
        packed, decoded = load(path or default_path()).encode_column(column)
        made = {
            "n_tokens": pa.array([len(x) // 4 for x in packed], pa.int64()),
            "ids_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in packed], pa.string()),
            "decoded_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in decoded], pa.string()),
        }
        if with_ids:
            ends = np.cumsum([0, *(len(x) // 4 for x in packed)]).astype(np.int32)
            made["token_ids"] = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(packed), "<i4")))
        return made

    return common.annotate(df, run, out, list(id_cols), text_col, done=lambda: load(path or default_path()).shrink())


def decode_ids(df: DataFrame, path: str | None = None, id_cols: tuple[str, ...] = ("doc_id",), ids_col: str = "token_ids") -> DataFrame:
    """``id_cols`` and ``decoded``: the text of an array of ids (null: empty text)."""
    from pyspark.sql import types as T

    schema = T.StructType([*(df.schema[c] for c in id_cols), T.StructField("decoded", T.StringType())])

    def run(batches):
        for b in batches:
            tok = load(path or default_path())
            plain = pa.array([tok.decode(x or []) for x in b.column(b.num_columns - 1).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], plain], names=schema.names)

    return df.select(*id_cols, ids_col).mapInArrow(run, schema)

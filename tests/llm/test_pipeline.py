"""The pipeline beside a brute-force version of all its stages, and on odd input."""

import hashlib
import re
import struct

import corpus_pipeline
import pytest
from pyspark.sql import functions as F
from test_nearcopies import survivors
from test_quality_rules import brute_verdicts

from recordlink.llm import bpe, common, mixing
from recordlink.llm.queries import TARGET

tokenizers = pytest.importorskip("tokenizers")


def common_lines_gone(texts, least=10):
    key = lambda x: re.sub("[A-Z]", lambda m: m[0].lower(), x.strip(" \t\n\x0b\x0c\r"))
    held = {}
    for t in texts.values():
        for k in {key(x) for x in t.split("\n")}:
            held[k] = held.get(k, 0) + 1
    return {i: "\n".join(x for x in t.split("\n") if not (key(x) and held[key(x)] >= least)) for i, t in texts.items()}


def prefix(spark, rows):
    """The ids that the mixture takes: each leaf's documents in its hashed order until the budget is used up."""
    order = {r["id"]: r["h"] & 0xFFFFFFFFFFFFFFFF for r in spark.createDataFrame([(i,) for i in rows], "id long").select("id", F.xxhash64(F.lit(TARGET.seed), F.lit(0), "id").alias("h")).collect()}
    leaves = {}
    for i, (text, lang, source) in rows.items():
        number = re.search(r"(\d+)$", source or "")
        path = (f"d{int(number[1]) % 4}" if number else mixing.NONE, lang or mixing.NONE, source if source is not None else mixing.NONE)
        leaves.setdefault(path, []).append((order[i], i, len(re.findall("[^\x20\x09-\x0d]+", text))))
    supply = {k: sum(n for _, _, n in v) for k, v in leaves.items()}
    out = set()
    for path, left in mixing.plan(supply, mixing.Target(TARGET.weights, budget_share=0.9, max_epochs=1)).items():
        if left >= supply[path] > 0:
            out |= {i for _, i, _ in leaves[path]}
            continue
        for _, i, n in sorted(leaves[path]):
            if left <= 0:
                break
            out.add(i)
            left -= n
    return out


def test_every_stage_and_the_whole_match_brute_force(spark, docs, sf_dir):
    library = tokenizers.Tokenizer.from_file(bpe.default_path())
    library.no_padding()
    library.no_truncation()
    rows = {r["doc_id"]: r for r in docs.collect()}
    verdicts = brute_verdicts([(r["lang"], r["text"]) for r in rows.values()])
    texts = {i: r["text"] or "" for i, r in rows.items() if verdicts[r["lang"], r["text"]][2]}
    assert 0 < len(texts) < len(rows)
    texts = common_lines_gone(texts)
    assert any(texts[i] != rows[i]["text"] for i in texts)
    one = set(survivors(texts))
    assert len(one) < len(texts)
    taken = prefix(spark, {i: (texts[i], rows[i]["lang"], rows[i]["source"]) for i in one})
    assert len(taken) < len(one)
    got = {r["doc_id"]: r for r in corpus_pipeline.run(spark, sf_dir).collect()}
    assert set(got) == taken
    for i, r in got.items():
        ids = library.encode(texts[i], add_special_tokens=False).ids
        assert r["token_ids"] == ids and r["n_tokens"] == len(ids) and (r["lang"], r["source"]) == (rows[i]["lang"], rows[i]["source"])
        assert r["ids_sha256"] == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()


def test_stages_keep_columns_of_any_name_and_take_odd_rows(spark, odd, none, docs):
    clash = docs.limit(60).select("*", *[F.lit(777).alias(c) for c in ("n_lines", "n_dropped", "kept_text", "kept", "n_words", "times", "copy", "p_domain", "domain", "component_id", "node")])
    for df in (clash, odd, none):
        now = df
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, now, "")
            if name == "bpe":
                assert out.count() == now.count()
                break
            assert out.columns == df.columns, name
            path = common.shared_folder(spark, name)
            out.write.parquet(path)
            now = spark.read.parquet(path)
        if df is clash:
            assert now.count() > 0 and now.where("n_lines <> 777 or times <> 777 or p_domain <> 777 or kept_text <> 777").count() == 0
            assert now.where("n_chars <> char_length(text)").count() == 0

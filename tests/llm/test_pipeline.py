import re

import corpus_pipeline as C
import numpy as np
import public_tokenizers as P
from pyspark.sql import functions as F
from test_operators import brute_removed
from test_shingles import brute_leaders
from tokenizers import Tokenizer

from tideline.llm import queries as Q

WORD = re.compile("[^\x20\x09-\x0D]+")


def test_each_stage_on_what_the_one_before_kept(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = [docs]
    for name, stage in C.STAGES:
        out = stage(spark, kept[-1], sf)
        out.write.parquet(str(tmp_path / name))
        kept.append(spark.read.parquet(str(tmp_path / name)))
    frames = [k.toPandas() for k in kept]
    assert all(list(f.columns) == C.COLUMNS for f in frames[:-1])
    # languages: only texts without a letter go
    assert set(frames[1].doc_id) == {d for d, t in zip(frames[0].doc_id, frames[0].text) if t and any(c.isalpha() for c in t)}
    # near duplicates: the smallest id of each group of texts that share 4/5 of their 5-word shingles stays
    a = frames[1].sort_values("doc_id")
    ids = a.doc_id.tolist()
    assert sorted(frames[2].doc_id) == sorted(ids[i] for i in brute_leaders(a.text))
    # passages
    want = brute_removed(set(zip(frames[2].doc_id, frames[2].text)), 50)
    text = dict(zip(frames[2].doc_id, frames[2].text))
    assert dict(zip(frames[3].doc_id, frames[3].text)) == {d: (k if r else text[d]) for d, (n, r, k) in want.items() if not r or r < n}
    # mixing: whole copies of unchanged documents
    assert set(zip(frames[4].doc_id, frames[4].text)) <= set(zip(frames[3].doc_id, frames[3].text)) and frames[4].doc_id.value_counts().max() <= 3
    # packing: every token of every copy, once
    tok = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    total = sum(len(e.ids) + 1 for e in tok.encode_batch(frames[4].text.tolist(), add_special_tokens=False))
    assert frames[5].length.sum() == total and np.max(frames[5].groupby("sequence_id").length.sum()) <= 2048


def test_queries_return_the_columns_of_their_contracts(spark, sf):
    want = {"op1": ["query_id", "rank", "vec_id", "score"], "op4": ["page_id", "host", "path", "rule", "verdict"], "op6": ["doc_id", "n_words", "n_removed", "kept_sha256"], "op9": ["doc_id", "held_out", "lang_pred", "score"]}
    for name, f in Q.QUERIES.items():
        if name.split("_")[0] in want:
            assert f(spark, sf).columns == want[name.split("_")[0]]


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def test_an_empty_corpus_and_one_without_languages(spark, sf):
    none = spark.createDataFrame([], SCHEMA)
    for _, stage in C.STAGES:
        assert stage(spark, none, sf).count() == 0
    odd = spark.createDataFrame([(1, "some words", None, "s", 10), (None, "more words", None, None, 10), (2, "12 !", None, "s", 4), (3, None, None, "s", None)], SCHEMA)
    assert sorted(r["text"] for r in C.identify_languages(spark, odd, sf).collect()) == ["more words", "some words"]


def test_null_and_repeated_ids_and_clashing_columns_pass_every_stage(spark, sf):
    base = spark.read.parquet(f"{sf}/documents.parquet").where("text is not null").limit(40).select(*C.COLUMNS)
    rows = base.unionByName(base.limit(3)).unionByName(base.limit(2).withColumn("doc_id", F.lit(None).cast("long")))
    docs = rows.withColumns({"n_words": F.lit("x"), "lang_pred": F.lit("x"), "score": F.lit("x"), "tag": F.lit("x"), "kept": F.lit("x"), "v": F.lit(1)})
    for name, stage in C.STAGES:
        docs = stage(spark, docs, sf)
        if name != "packing":
            assert docs.where("doc_id is null").count() >= 1 and docs.columns == C.COLUMNS
            docs = docs.withColumns({"h": F.lit(1), "c": F.lit(2), "__hash": F.lit(3)})
    assert docs.count() > 0

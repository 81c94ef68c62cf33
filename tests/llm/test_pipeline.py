"""The pipeline stage by stage against plain versions, and the registered SQL."""

import duckdb
import numpy as np
import public_tokenizers as P

import corpus_pipeline
from incrank.llm import neardup, packing, queries, suffix, toxicity
from incrank.llm.common import stored, texts_of

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, rows = docs.columns, {r["doc_id"]: r for r in docs.collect()}
    done = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stored(stage(spark, docs, SF), name.replace(" ", "-"))
        done[name] = docs
        if name != "packing":
            assert docs.columns == columns
    # toxicity: what the scores say
    scores = toxicity.score_documents(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet"))
    kept = {r["doc_id"] for r in scores.where("predicted = 0").collect()}
    assert {r["doc_id"] for r in done["toxicity"].collect()} == kept
    # exact copies: the largest doc_id of each text
    last = {}
    for i in sorted(kept):
        last[rows[i]["text"].lower() if rows[i]["text"].isascii() else "".join(c.lower() if "A" <= c <= "Z" else c for c in rows[i]["text"])] = i
    assert {r["doc_id"] for r in done["exact dedup"].collect()} == set(last.values())
    # near copies: the smallest doc_id of each class
    before = [(r["doc_id"], r["text"]) for r in done["exact dedup"].collect()]
    from test_operators import brute_classes, brute_repeats

    weights = neardup.idf_weights(*neardup.document_frequencies(texts_of(done["exact dedup"])))
    assert {r["doc_id"] for r in done["near dedup"].collect()} == set(brute_classes(sorted(before), weights).values())
    # repeats
    before = [(r["doc_id"], r["text"]) for r in done["near dedup"].collect()]
    want = brute_repeats(before)
    after = {r["doc_id"]: r for r in done["suffix dedup"].collect()}
    assert set(after) == {i for i, _ in before}
    for i, t in before:
        gone = len(t.encode()) - len(after[i]["text"].encode())
        assert want[i][1] - 6 * want[i][2] <= gone <= want[i][1] and after[i]["n_chars"] == len(after[i]["text"])
    assert suffix.repeat_digests(done["near dedup"]).agg({"n_removed": "sum"}).first()[0] == sum(w[1] for w in want.values())
    # packing
    tokenizer = packing.word_encoder(P.path("word_bpe_49k.json")).tokenizer
    total = sum(len(tokenizer.encode(r["text"], add_special_tokens=False).ids) + 1 for r in after.values())
    assert done["packing"].agg({"length": "sum"}).first()[0] == total


def test_registered_queries(spark):
    import __spark_entry__ as e

    names = [n for n in e.queries() if n.startswith("op") and n[2].isdigit()]
    assert sorted({int(n[2:].split("_")[0]) for n in names}) == list(range(1, 11)) and "pipeline" in e.queries()
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS FROM '{SF}/documents.parquet'")
    for name, sql in queries.oracle_sql().items():
        got = queries.queries()[name](spark, SF).toPandas().sort_values("doc_id", ignore_index=True)
        want = c.sql(sql).df().sort_values("doc_id", ignore_index=True)[list(got.columns)]
        assert np.array_equal(got.values, want.values)

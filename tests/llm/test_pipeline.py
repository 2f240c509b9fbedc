"""The pipeline's stages: columns, decisions, and what clean documents keep."""

from collections import Counter

import corpus_pipeline
from pyspark.sql import functions as F

from spectral_ridge.llm import byte_bpe, queries, ranking, trie_join

SF = "/root/testdata/sf0.001"


def test_stages_in_order(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, {}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "lines", "near_duplicates", "mixture", "tokens"]
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        out.write.parquet(f"file://{tmp_path}/{name}")
        seen[name], docs = docs, spark.read.parquet(f"file://{tmp_path}/{name}")
        if name != "tokens":
            assert docs.columns == columns
    model = ranking.train_on_tables(spark, seen["quality"], SF)
    good = {r.doc_id for r in ranking.score_documents(seen["quality"], model).where("predicted = 1").collect()}
    assert {r.doc_id for r in seen["lines"].collect()} == good

    linked = trie_join.link_documents(seen["near_duplicates"]).collect()
    assert {r.doc_id for r in seen["mixture"].collect()} == {r.doc_id for r in linked if r.doc_id == r.component_id}

    mixed = Counter(r.doc_id for r in seen["tokens"].collect())
    assert set(mixed) == {r.doc_id for r in seen["mixture"].collect()} and max(mixed.values()) <= 2

    back = byte_bpe.decode_documents(docs, corpus_pipeline.RANKS)
    assert Counter((r.doc_id, r.text) for r in back.collect()) == Counter((r.doc_id, r.text) for r in seen["tokens"].collect())


def test_stages_on_odd_rows(spark, odd_docs, no_docs, tmp_path):
    plain = odd_docs.select("doc_id", "text", "lang", "source", "n_chars")
    for docs in (plain, no_docs.select(*plain.columns)):
        for name, stage in corpus_pipeline.STAGES[1:]:
            out = stage(spark, docs, SF)
            path = f"file://{tmp_path}/{name}-{docs.count()}"
            out.write.parquet(path)
            docs = spark.read.parquet(path)
        assert docs.count() >= 0


def test_line_stage_drops_only_emptied_documents(spark):
    line = "A line of text that is long enough to count as one and that comes twice in this small collection"
    docs = spark.createDataFrame([(1, line, "en", "s", len(line)), (2, line, "en", "s", len(line)), (3, "", "en", "s", 0), (4, f"{line}\nand a second line that is found only here", "en", "s", 0)], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: (r.text, r.n_chars) for r in corpus_pipeline.lines(spark, docs, SF).collect()}
    assert got == {1: (line, len(line)), 3: ("", 0), 4: ("and a second line that is found only here", 41)}


def test_line_stage_takes_repeats_of_short_lines(spark, tmp_path):
    line = "A line of text that is long enough to count as one and that comes twice in this small collection"
    rows = [(1, f"Title here\n\n{line}\nThe end"), (2, f"Title here\n\n{line}\nThe end"), (3, "Own title\nThe end"), (None, "The end")]
    docs = spark.createDataFrame([(*r, "en", "s", len(r[1])) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r.doc_id: r.text for r in corpus_pipeline.lines(spark, docs, SF).collect()} == {1: rows[0][1], 3: "Own title", None: "The end"}
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: (r.text, r.n_removed) for r in queries.op9_line_dedup(spark, str(tmp_path)).collect()}
    assert got == {1: (rows[0][1], 0), 2: ("", 3), 3: ("Own title", 1), None: ("The end", 0)}


def test_run_returns_tokens(spark):
    out = corpus_pipeline.run(spark, SF)
    assert out.columns == ["doc_id", "n_tokens", "tokens", "token_offsets"]
    assert out.where(F.size("tokens") != F.col("n_tokens")).count() == 0

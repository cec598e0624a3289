"""The corpus pipeline, stage by stage and as a whole."""

from __future__ import annotations

import collections

import sentencepiece

import corpus_pipeline
from collanom.llm import pieces
from collanom.llm.common import stored


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, before = docs.columns, docs
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "SimHash near-dedup", "benchmark decontamination", "SentencePiece encoding"]
    counts = [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stored(stage(spark, before, sf))
        assert docs.columns == columns and docs.schema == before.schema
        assert docs.select("doc_id").subtract(before.select("doc_id")).count() == 0
        counts.append(docs.count())
        before = docs
    assert counts[0] > counts[1] == counts[2] > counts[3] >= counts[4]
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert len(set(texts.values())) == len(texts)
    library = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    last = {r["doc_id"]: r["ids"] for r in corpus_pipeline.run(spark, sf).collect()}
    assert last.keys() == texts.keys()
    for doc in list(texts)[:200]:
        assert last[doc] == library.encode(texts[doc] or "")


def _rows(df):
    return sorted(map(repr, (tuple(r) for r in df.collect())))


def test_awkward_rows(spark, sf, awkward, empty):
    """Nulls, blanks, ties, repeated rows, a long text and clashing names: what every stage does with them."""
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, awkward, sf)
        assert stage(spark, empty, sf).count() == 0
        if name == "SentencePiece encoding":
            rows = {r["doc_id"]: r["n_tokens"] for r in out.collect()}
            assert rows[1] == rows[2] == 0 and rows[6] >= 60_000 and out.count() == awkward.count()
        elif name == "SimHash near-dedup":
            kept = [r["doc_id"] for r in out.collect()]
            # texts without words are one group, the repeated row is one, and a row without an id stays
            assert sorted(kept, key=repr) == sorted([1, 4, 6, 7, None], key=repr) and out.schema == awkward.schema
        else:
            assert out.schema == awkward.schema
            assert _rows(out.drop("n_chars")) == _rows(awkward.drop("n_chars"))


def plain_run(spark, sf):
    """The rows that the stages leave, by plain versions of the exact ones on what the learned and probabilistic ones keep."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r["doc_id"]: (r["source"], r["text"]) for r in corpus_pipeline.toxicity_filter(spark, docs, sf).collect()}
    pages, holders = collections.Counter(s for s, _ in kept.values()), collections.Counter()
    for source, text in kept.values():
        holders.update({(source, line) for line in (text or "").split("\n") if line.strip()})
    common = {k for k, n in holders.items() if n >= 3 and n > 0.05 * pages[k[0]]}
    return {i: None if t is None else "\n".join(x for x in t.split("\n") if (s, x) not in common) for i, (s, t) in kept.items()}


def test_first_stages_against_a_plain_version(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    after = corpus_pipeline.line_dedup(spark, corpus_pipeline.toxicity_filter(spark, docs, sf), sf)
    assert {r["doc_id"]: r["text"] for r in after.collect()} == plain_run(spark, sf)

"""The pipeline against plain versions of its stages, each on what the stage before it left."""

import re
from collections import Counter

import corpus_pipeline
from eqdict.llm import language, mixing
from eqdict.llm.common import staged, workdir
from eqdict.llm.queries import byte_bpe
from tests.llm.test_texts import plain_groups
from tests.llm.test_tokens import check_packing


def test_stages(spark, small):
    from tokenizers import Tokenizer

    df, _ = small
    docs, before, work = df, None, workdir(spark, "test-pipeline")
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, staged(stage(spark, docs, ""), f"{work}/{name}")
        rows, had = docs.collect(), before.collect()
        if name != "best_fit_packing":
            assert docs.columns == df.columns
        if name == "language_id":
            profiles = language.fit(language.training_rows(before, "doc_id", "text", "lang"))
            assert Counter(r.doc_id for r in rows) == Counter(r.doc_id for r in had if profiles.judge(r.text)[0] != "und")
        if name == "exact_copies":
            first = {}
            for r in sorted(had, key=lambda r: r.doc_id):
                first.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", r.text or ""), r.doc_id)
            assert sorted(r.doc_id for r in rows) == sorted(first.values())
        if name == "near_copies":
            assert sorted(r.doc_id for r in rows) == sorted(g[0] for g in plain_groups([(r.doc_id, r.text) for r in had], 5, 80) if g[3])
        if name == "source_mixing":
            assert Counter(map(tuple, rows)) == Counter(map(tuple, mixing.mixed(before.repartition(3)).collect())) and {r.doc_id for r in rows} <= {r.doc_id for r in had}
        if name == "best_fit_packing":
            t = Tokenizer.from_file(byte_bpe())
            check_packing([(r.doc_id, r.text) for r in had], rows, lambda s: t.encode(s, add_special_tokens=False).ids, 2048)


def test_run(spark, sf):
    got = corpus_pipeline.run(spark, sf)
    assert got.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"] and got.count() > 0


def test_odd_rows_and_empty_tables(spark, edge, empty):
    for docs in (edge, empty):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            docs = staged(stage(spark, docs, ""), f"{workdir(spark, 'odd')}/{name}")
            assert docs.columns == edge.columns
        packed = corpus_pipeline.STAGES[-1][1](spark, docs, "")
        assert (packed.count() > 0) == (docs.count() > 0)

"""The pipeline, stage by stage, against plain versions of each decision."""

import hashlib

import corpus_pipeline
from tests.llm.test_operators import plain_components, plain_hits, plain_secrets
from tolerant_gd.llm import ppm_language
from tolerant_gd.llm.tables import table, tokenizer_path


def test_stages_one_after_another(spark, sf):
    from tokenizers import Tokenizer

    docs = table(spark, sf, "documents")
    columns = docs.columns
    bench = [tuple(r) for r in table(spark, sf, "benchmark").collect()]
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_copies", "benchmark_leaks", "secrets", "tokens"]
    kept = dict(corpus_pipeline.STAGES)["language"](spark, docs, sf)
    und = {r.doc_id for r in ppm_language.identify(docs).collect() if r.lang_pred == "und" or r.score < 0.5 or r.bits_per_byte > 7}
    rows = [tuple(r) for r in kept.collect()]
    assert kept.columns == columns
    assert {r[0] for r in rows} == {r.doc_id for r in docs.select("doc_id").collect()} - und
    one = corpus_pipeline.near_copies(spark, kept, sf)
    least = {d for d, _, c in plain_components([(r[0], r[1]) for r in rows]) if d == c}
    assert sorted(r.doc_id for r in one.collect()) == sorted(least)
    assert one.columns == columns
    clean = corpus_pipeline.benchmark_leaks(spark, one, sf)
    leaks = {h[0] for h in plain_hits([(r.doc_id, r.text) for r in one.collect()], bench) if h[5]}
    assert {r.doc_id for r in clean.collect()} == least - leaks
    assert leaks
    masked = corpus_pipeline.secrets(spark, clean, sf)
    assert masked.columns == columns
    after = {r.doc_id: r.text for r in masked.collect()}
    for r in clean.collect():
        out, at = [], 0
        for a, _, b in plain_secrets(r.text)[1]:
            if a >= at:
                out += [r.text[at:a], "[SECRET]"]
            at = max(at, b)
        assert after[r.doc_id] == "".join([*out, r.text[at:]])
    library = Tokenizer.from_file(tokenizer_path())
    final = corpus_pipeline.run(spark, sf)
    assert {r.doc_id for r in final.collect()} == set(after)
    for r in final.collect():
        ids = library.encode(after[r.doc_id], add_special_tokens=False).ids
        assert (r.n_tokens, r.ids_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest())


def test_empty_corpus(spark, sf):
    docs = table(spark, sf, "documents").where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, sf).count() == 0


def test_core_stands_alone():
    """Nothing outside the subpackage imports it."""
    import pathlib
    import re

    root = pathlib.Path(corpus_pipeline.__file__).parent / "tolerant_gd"
    for p in root.rglob("*.py"):
        if "llm" not in p.parts:
            assert not re.search(r"tolerant_gd\.llm|corpus_pipeline", p.read_text()), p

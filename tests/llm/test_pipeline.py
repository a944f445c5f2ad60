"""The pipeline's stages on the smallest tables, each judged on its own input."""

import corpus_pipeline
from sortbit.llm import queries
from sortbit.llm.base import keep, read
from sortbit.llm.line_dedup import MIN_CHARS

from .test_operators import brute_components, brute_lines, check_pieces
from sortbit.llm.packing import Limits


def by_id(df):
    return {r.doc_id: r.text for r in df.collect()}


def test_stages(spark, sf_dir):
    docs = read(spark, sf_dir, "documents").limit(90)
    columns, stage = docs.columns, dict(corpus_pipeline.STAGES)
    assert list(stage) == ["toxicity", "line_dedup", "near_dedup", "decontaminate", "packing"]
    kept = keep(stage["toxicity"](spark, docs, sf_dir))
    assert kept.columns == columns and 0 < kept.count() <= 90
    lines = keep(stage["line_dedup"](spark, kept, sf_dir))
    assert lines.columns == columns and by_id(lines) == brute_lines(by_id(kept), MIN_CHARS)
    assert lines.where("n_chars <> length(text)").count() == 0
    near = keep(stage["near_dedup"](spark, lines, sf_dir))
    assert near.columns == columns and set(by_id(near)) == {d for d, (_, c) in brute_components(by_id(lines)).items() if c == d}
    clean = keep(stage["decontaminate"](spark, near, sf_dir))
    assert clean.columns == columns and set(by_id(clean)) <= set(by_id(near))
    check_pieces(stage["packing"](spark, clean, sf_dir).collect(), by_id(clean), Limits())


def test_queries_with_sql(same):
    for name, sql in queries.ORACLES.items():
        same(name, queries.QUERIES[name], sql)


def test_ten_queries():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.QUERIES) == list(range(1, 11))

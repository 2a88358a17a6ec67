"""The pipeline's stages, one after another on a small table, each against a plain form of its own."""

import zlib
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from tests.llm.test_operators import brute_components, ids, text
from ugraph.llm import mixing, pii, quality_rules


@pytest.fixture(scope="module")
def sf_dir(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("sf"))
    rows = [(i, text(i, 70 + i % 9), "en", ["b", "a", None][i % 3], 1) for i in range(60)]
    rows += [(100 + i, text(i, 70 + i % 9) + " tail", "en", "a", 1) for i in range(0, 60, 7)]
    rows += [(5, text(5, 75), "en", "a", 1), (5, text(90, 80), "en", "a", 1), (None, text(91, 80), "en", "b", 1), (None, text(91, 80), None, "b", 1)]
    rows += [(200 + i, " ".join(w + "$$$" for w in text(300 + i, 80).split()), "en", "b", 1) for i in range(20)]
    rows += [(300, None, "en", "a", None), (301, "", None, None, 0), (302, "short", "en", "a", 5), (303, text(95, 5000), "en", "b", 1), (304, text(96, 80) + " jo.x@example.org 2021-03-04", "en", "a", 1)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(r[0], int(not 200 <= r[0] < 220), 0) for r in rows if r[0] is not None and r[0] % 2 == 0], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, stages = docs.columns, dict(corpus_pipeline.STAGES)
    held = lambda df: sorted(map(tuple, df.collect()), key=repr)

    good = stages["quality"](spark, docs, sf_dir)
    assert good.columns == columns
    verdict = Counter((r.doc_id, r.n_words) for r in quality_rules.quality_digest(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).filter("kept").collect())
    assert Counter((r.doc_id, len(r.text.split())) for r in good.collect()) == verdict
    assert not {r.doc_id for r in good.collect()} & {300, 301, 302, *range(200, 220)} and {303, 304} < {r.doc_id for r in good.collect()}

    once = stages["near_dedup"](spark, good, sf_dir)
    rows = sorted(good.collect(), key=lambda r: (r.doc_id is None, r.doc_id or 0))
    roots = brute_components([(i, r.text) for i, r in enumerate(rows)], corpus_pipeline.STAGE_PERCENT, corpus_pipeline.STAGE_WORDS)
    want = [tuple(r) for i, r in enumerate(rows) if roots[i] == i]
    assert once.columns == columns and Counter(r.text for r in once.collect()) == Counter(r[1] for r in want)
    assert Counter(r.doc_id for r in once.collect()) == Counter(r[0] for r in want)

    safe = stages["personal_data"](spark, once, sf_dir)
    assert held(safe) == held(pii.masked(once, pii.session_key(spark))) and safe.columns == columns
    changed = [r for r in safe.collect() if r.doc_id == 304]
    assert len(changed) == 1 and "2021-03-04" not in changed[0].text and changed[0].text.startswith(text(96, 80))

    mixed = stages["mixing"](spark, safe, sf_dir)
    copies = mixing.with_copies(safe.withColumn("mix_size", mixing.word_count(safe.text))).collect()
    assert Counter((r.doc_id, r.text) for r in mixed.collect()) == Counter({(r.doc_id, r.text): r.mix_copies for r in copies if r.mix_copies}) and mixed.columns == columns

    pieces = stages["packing"](spark, mixed, sf_dir).toPandas()
    streams = Counter(ids(r.text).tobytes() for r in mixed.collect())
    assert pieces.length.sum() == sum(len(k) // 4 * n for k, n in streams.items())
    assert all(zlib.crc32(r.ids) == r.ids_crc32 for r in pieces.itertuples())
    for _, g in pieces.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == np.concatenate(([0], np.cumsum(g.length)[:-1])).tolist() and g.length.sum() <= 2048


def test_run(spark, sf_dir):
    out = corpus_pipeline.run(spark, sf_dir)
    assert out.count() > 40 and {"doc_id", "start", "length", "sequence_id", "offset", "ids"} <= set(out.columns)

"""The pipeline's stages, each against brute force on its own input."""

import re
import zlib

import corpus_pipeline
import numpy as np
import pyarrow as pa
from sparsepairs.llm import near_duplicates, secret_scan, shared, toxicity
from sparsepairs.llm.batches import text_bytes
from sparsepairs.llm.tokens import encoder


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    known = {r["doc_id"]: r for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = shared.written(stage(spark, docs, sf), "test-stage")
        assert out.columns == columns, name
        before, after = ({r["doc_id"]: r["text"] for r in d.collect()} for d in (docs, out))
        assert set(after) <= set(before)
        if name == "quality":
            bad = {i for i, r in known.items() if r["quality"] == 0}
            assert len(bad & set(after)) <= len(bad) * 0.2 and len(set(before) - set(after) - bad) < 0.2 * len(before)
        elif name == "toxicity":
            model = toxicity.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"))
            scores = toxicity.scores(model, *toxicity.word_keys(*text_bytes(pa.array(list(before.values())))))
            langs = [r["lang"] for r in docs.collect()]
            cut = [model.thresholds.get(x, model.threshold) for x in langs]
            assert set(after) == {i for i, x, t in zip(before, scores, cut, strict=True) if x < t}
        elif name == "near copies":
            found = {r["doc_id"]: r["class_id"] for r in near_duplicates.classes(docs).collect()}
            assert set(after) == set(found.values())
        elif name == "secrets":
            assert set(after) == set(before)
            assert not any(r["n_hex"] or r["n_access"] for r in secret_scan.scan_secrets(out).collect())
            assert any(re.search("<(assign|hex)>", t) for t in after.values()) or after == before
        docs = out
    packed = corpus_pipeline.packed(spark, docs, sf).collect()
    encode, at = encoder().ids, {}
    ids = {i: np.append(encode(t), np.uint32(0)).astype("<u4") for i, t in after.items()}
    for r in sorted(packed, key=lambda r: (r["doc_id"], r["start"])):
        assert r["start"] == at.get(r["doc_id"], 0) and r["doc_tokens"] == len(ids[r["doc_id"]])
        at[r["doc_id"]] = r["start"] + r["length"]
        assert r["ids_crc32"] == zlib.crc32(ids[r["doc_id"]][r["start"] : at[r["doc_id"]]].tobytes())
    assert at == {i: len(x) for i, x in ids.items()}
    room = {}
    for r in sorted(packed, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == room.get(r["sequence_id"], 0)
        room[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(room.values()) <= 1024 and sum(room.values()) / (1024 * len(room)) > 0.97


def test_stages_on_edge_rows(spark, sf):
    """Nulls in any column, empty and very long texts, ties, repeated rows and ids, clashing columns, empty tables."""
    long, plain = "lang wort " * 20_000, " ".join(f"wort{i}" for i in range(80))
    rows = [(i, t, None, None, None, 1.0, 2) for i, t in enumerate([None, "", " \n", "a", plain, plain, long])]
    rows += [(4, plain, None, None, None, 1.0, 2), (4, "another text of this id", None, None, None, 1.0, 2), (None, plain, "de", "s", 3, None, None), (None, None, None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double, component int")
    empty = docs.limit(0)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and stage(spark, empty, sf).count() == 0, name
        if name in ("quality", "toxicity"):
            # No labelled row: the quality score is 0.5 for all, the toxicity score just below.
            assert out.count() == len(rows), name
    left = [(r["doc_id"], r["text"]) for r in corpus_pipeline.near_copies(spark, docs, sf).collect()]
    assert sorted(left, key=str) == sorted([(0, None), (1, ""), (2, " \n"), (3, "a"), (4, plain), (4, "another text of this id"), (6, long), (None, None)], key=str)
    packed = corpus_pipeline.packed(spark, docs, sf).collect()
    assert sum(r["length"] == r["doc_tokens"] == 1 for r in packed) == 3 and corpus_pipeline.packed(spark, empty, sf).count() == 0


def test_a_repeated_row_stays_once(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(5)
    out = corpus_pipeline.near_copies(spark, docs.unionByName(docs), sf)
    assert out.count() == out.select("doc_id").distinct().count() > 0


def test_stage_names_and_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "toxicity", "near copies", "secrets", "packing"] and corpus_pipeline.ORACLE_SQL is None

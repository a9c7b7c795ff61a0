"""The pipeline's stages on a small table with planted cases."""

from __future__ import annotations

import corpus_pipeline


def test_stages(spark, tmp_path):
    text = " ".join(f"word{i} the" for i in range(40))
    rows = [(i, f"{text} and number {chr(97 + i % 26)}{i}", "en", f"s{i % 3}", 9) for i in range(1, 20)]
    rows += [(50, text.replace("word3 ", "sword "), "en", "s0", 1), (51, None, None, "s0", None), (52, "12 34", "en", "s1", 5), (53, "so mail joe.1@mail.example.com today", None, None, 4), (None, "no id here", "en", "s1", 3)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    columns, kept = docs.columns, {}
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stage(spark, docs, str(tmp_path))
        if i < 4:
            assert docs.columns == columns
        docs.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        kept[name] = docs.collect()
    ids = [r["doc_id"] for r in kept["language_id"]]
    assert len(ids) == 22 and not {51, 52} & set(ids)
    # all numbered texts and 50 are near copies: the smallest id stays
    assert sorted(str(r["doc_id"]) for r in kept["near_duplicates"]) == ["1", "53", "None"]
    mail = next(r for r in kept["personal_data"] if r["doc_id"] == 53)
    assert mail["text"] == "so mail [EMAIL] today" and mail["n_chars"] == 21 and mail["lang"] == "en"
    assert kept["mixing"] and {"ids", "n_pieces"} <= set(kept["pieces"][0].asDict())
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == len(kept["pieces"])


def test_empty(spark, tmp_path):
    spark.createDataFrame([], "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0

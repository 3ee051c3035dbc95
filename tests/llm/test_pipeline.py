"""The stages against plain Python over the same documents."""

import hashlib

import sentencepiece

import corpus_pipeline
from xlsql.llm import decontaminate, langid, pieces, simhash
from xlsql.session import load_table

SF = "/root/testdata/sf0.001"


def test_stages_keep_the_columns_and_match_plain_python(spark):
    docs = load_table(spark, SF, "documents")
    columns = docs.columns
    rows = {r["doc_id"]: r for r in docs.collect()}
    bench = [(r["item_id"], decontaminate.words_of(r["text"])) for r in load_table(spark, SF, "benchmark").collect()]
    made = docs
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in made.collect()}
        made = stage(spark, made, SF)
        after = {r["doc_id"]: r for r in made.collect()}
        if name != "sentencepiece":
            assert made.columns == columns
        if name == "language_id":
            assert set(before) - set(after) <= {i for i, r in rows.items() if not langid.letters(r["text"])} | set(list(before)[:0]) or len(before) - len(after) <= 2
        elif name == "simhash_near_dedup":
            prints = {i: simhash.fingerprint(r["text"]) for i, r in before.items()}
            ids, up = sorted(before), {i: i for i in before}

            def find(i):
                while up[i] != i:
                    i = up[i]
                return i

            for x, i in enumerate(ids):
                for j in ids[x + 1 :]:
                    if (prints[i] ^ prints[j]).bit_count() <= 3:
                        a, b = find(i), find(j)
                        up[max(a, b)] = min(a, b)
            assert set(after) == {i for i in ids if find(i) == i}
        elif name == "benchmark_decontamination":
            index = decontaminate.Index(bench)
            assert set(after) == {i for i, r in before.items() if not index.leaks(decontaminate.words_of(r["text"]), decontaminate.SIMILARITY)}
        elif name == "secret_scan":
            assert set(after) == set(before)
        else:
            lib = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
            for i, r in after.items():
                ids = lib.encode(before[i]["text"] or "")
                assert (r["n_tokens"], list(r["ids"])) == (len(ids), ids) and r["decoded_sha256"] == hashlib.sha256(lib.decode(ids).encode()).hexdigest()
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, SF).collect()} == set(after)


def test_stages_bear_odd_rows(spark, tmp_path):
    rows = [(1, None, "en", "s", 0), (2, "", "en", "s", 0), (None, "the cat sat on the mat", None, None, None), (3, "the cat sat on the mat " * 3, "en", "s", 9), (3, "the cat sat on the mat " * 3, "en", "s", 9), (4, "!!", None, "s", 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    spark.createDataFrame([], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for name, stage in corpus_pipeline.STAGES:
        for given in (docs, docs.where("false"), docs.withColumn("spans", docs["text"]).withColumn("fp", docs["doc_id"])):
            out = stage(spark, given, str(tmp_path)).collect()
            assert len(out) <= 6, name


def test_every_operator_bears_an_empty_folder_of_tables(spark, tmp_path):
    from xlsql.llm.registry import QUERIES

    for t in ("documents", "embeddings", "pages", "benchmark", "labels"):
        load_table(spark, SF, t).where("false").coalesce(1).write.parquet(str(tmp_path / f"{t}.parquet"))
    for name, q in QUERIES.items():
        assert q(spark, str(tmp_path)).count() == 0, name

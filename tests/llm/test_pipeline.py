import random

import corpus_pipeline
import pyarrow as pa
from levelsort.llm import common, exact_dedup, ngram_join, packing, queries, secrets, toxicity

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def corpus(n=60):
    rnd = random.Random(5)
    words = [f"w{i}" for i in range(3000)]
    rows, labels = [], []
    for i in range(n):
        text = " ".join(rnd.choice(words) for _ in range(80))
        if i % 10 == 3:
            text = f"you {rnd.choice(['blarg', 'snorf'])}. " * 6 + text
        rows.append([i, text])
        labels.append((i, int(i % 10 == 3)))
    rows.append([100, rows[0][1].replace(" ", "  ", 4)])  # an exact copy but for white space
    rows.append([101, " ".join(rows[1][1].split()[:-1] + ["changed"])])  # a near copy
    rows.append([102, "password = hunter2hunter2 and " + rows[2][1][:200]])
    rows += [[103, None], [104, ""], [None, "no id at all"], [105, "long " * 9000], [0, rows[0][1]]]
    return [(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], labels


def written(spark, tmp_path, rows, labels):
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    return str(tmp_path)


def test_stages_against_brute_force(spark, tmp_path):
    rows, labels = corpus()
    d = written(spark, tmp_path, rows, [(i, None, y) for i, y in labels])
    docs, names = common.table(spark, d, "documents"), SCHEMA.replace(",", "").split()[::2]
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = common.Stage(stage(spark, docs, d), f"test-{name}").df
        seen[name] = docs.collect()
        if name != "packing":
            assert docs.columns == names
    ids = {k: sorted((r["doc_id"] for r in v), key=str) for k, v in seen.items()}
    toxic = {i for i, y in labels if y}
    assert set(ids["toxicity"]) == {r[0] for r in rows} - toxic
    texts, kept = {}, set()
    for r in sorted(seen["toxicity"], key=lambda r: (r["doc_id"] is None, r["doc_id"])):
        key = " ".join(x for x in (r["text"] or "").replace("\n", " ").split(" ") if x)
        if key not in texts:
            texts[key] = r["doc_id"]
            kept.add(r["doc_id"])
    assert ids["exact_dedup"] == sorted(kept, key=str) and 100 not in kept and 104 not in kept and 103 in kept
    sets = {r["doc_id"]: set(ngram_join.shingle_hashes(r["text"]).tolist()) for r in seen["exact_dedup"] if r["doc_id"] is not None}
    near = {max(a, b) for a in sets for b in sets if a != b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])}
    assert 101 in near and ids["ngram_join"] == sorted(kept - near, key=str)
    clean = {r["doc_id"]: r for r in seen["secrets"]}
    assert "hunter2" not in clean[102]["text"] and clean[102]["n_chars"] == len(clean[102]["text"])
    pieces = {}
    for r in seen["packing"]:
        pieces.setdefault(r["doc_id"], []).append(r)
    assert set(pieces) == set(clean)
    for parts in pieces.values():
        parts.sort(key=lambda r: r["start"])
        at = 0
        for p in parts:
            assert p["start"] == at
            at += p["length"]
        assert at == parts[0]["doc_tokens"]
    windows = {}
    for r in seen["packing"]:
        windows.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for w in windows.values():
        at = 0
        for offset, length in sorted(w):
            assert offset == at
            at += length
        assert at <= packing.WINDOW
    assert [r["doc_id"] for r in corpus_pipeline.run(spark, d).select("doc_id").distinct().collect()].__len__() == len(pieces)


def test_empty_tables(spark, tmp_path):
    d = written(spark, tmp_path, [], [])
    assert corpus_pipeline.run(spark, d).count() == 0
    docs = common.table(spark, d, "documents")
    assert queries.QUERIES["op1_toxicity"](spark, d).count() == 0
    for op in ("op2_licences", "op3_subword", "op4_packing", "op6_secrets", "op7_ngram_join", "op8_exact_dedup", "op9_media", "op10_line_dedup"):
        assert queries.QUERIES[op](spark, d).count() == 0, op
    assert secrets.redact(docs).count() == 0 and toxicity.drop_toxic(docs, toxicity.train(docs, common.table(spark, d, "labels"))).count() == 0


def test_clashing_columns_come_through(spark):
    rows = [(1, "a b c d e f g", "x", 1), (2, "a  b c d e f g", "y", 2), (3, "password: abcdefgh1", "z", 3), (None, None, None, None)]
    names = ["_sha", "_stay_id", "_stay", "_stay_sha", "_text", "_hit", "_base", "_spans", "hashes", "sid", "n", "_id", "y", "score"]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, tag string, m int")
    for i, c in enumerate(names):
        df = df.withColumn(c, corpus_pipeline.F.lit(i))
    for out, ids in ((exact_dedup.drop_copies(df), {1, 3, None}), (ngram_join.keep_one_per_component(df), {1, 3, None}), (secrets.redact(df), {1, 2, 3, None})):
        assert out.columns == df.columns
        got = out.collect()
        assert {r["doc_id"] for r in got} == ids and all(r[c] == i for r in got for i, c in enumerate(names))


def test_python_maps_of_a_stage_get_short_batches(spark):
    """10,000 whole texts in one batch are tens of MB in the JVM and in each worker."""
    key, docs = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.range(0, 5000, 1, 1).selectExpr("id as doc_id", "repeat('some words ', 50) as text")

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows], pa.int64())], ["n"])

    before = spark.conf.get(key)
    got = [r["n"] for r in common.Stage(docs.mapInArrow(sizes, "n long"), "test-batches").df.collect()]
    assert sum(got) == 5000 and max(got) <= common.ARROW_ROWS and spark.conf.get(key) == before
    spark.conf.set(key, "100")
    try:
        got = [r["n"] for r in common.Stage(docs.mapInArrow(sizes, "n long"), "test-batches").df.collect()]
        assert sum(got) == 5000 and max(got) <= 100 and spark.conf.get(key) == "100"
    finally:
        spark.conf.unset(key)


def test_maps_give_memory_back(monkeypatch):
    """a worker serves all stages, so what one task frees must not stay in its pools."""
    seen = []
    monkeypatch.setattr(common, "give_back", lambda: seen.append("back"))
    run = packing._pieces(queries.tokenizer_path(queries.WORD_BPE), 4096, 2, False)
    docs = pa.RecordBatch.from_arrays([pa.array([1, 2]), pa.array(["one text", None])], ["doc_id", "text"])
    for x in common.lean(run)(iter([docs])):
        seen.append(x.num_rows)
    assert seen == ["back", 2, "back"]

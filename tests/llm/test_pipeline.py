import corpus_pipeline
from relanom.llm import decontaminate, packing, pii

SF = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(9001, None, "en", "s", 0), (9002, "123 !!", None, None, None), (9003, "", "en", "s", 0)], docs.schema)
    before = docs.unionByName(odd)
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = corpus_pipeline.scratch.table(stage(spark, before, SF), name)
        assert after.columns == docs.columns
        kept[name] = {r.doc_id: r.text for r in after.collect()}
        before = after
    all_docs = {r.doc_id: r.text for r in docs.collect()}
    assert set(kept["language_id"]) == {d for d, t in all_docs.items() if t and any(c.isalpha() for c in t)}
    words = lambda t: tuple(decontaminate.words_of(t.encode()))
    assert {words(t) for t in kept["near_dedup"].values()} <= {words(t) for t in kept["language_id"].values()}
    assert len({words(t) for t in kept["near_dedup"].values()}) == len(kept["near_dedup"]) < len(kept["language_id"])
    items = [words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    windows = {w[i : i + 10] for w in items for i in range(max(1, len(w) - 9)) if w}
    sizes = {len(w) for w in windows}
    holds = lambda t: any(words(t)[i : i + n] in windows for n in sizes for i in range(len(words(t)) - n + 1))
    assert set(kept["decontamination"]) == {d for d, t in kept["near_dedup"].items() if not holds(t)} and len(kept["decontamination"]) < len(kept["near_dedup"])
    assert set(kept["pii"]) == set(kept["decontamination"])
    assert any(kept["pii"][d] != t for d, t in kept["decontamination"].items())
    encode = packing.encoder(packing.default_paths()[0], None)
    packed = corpus_pipeline.STAGES[-1][1](spark, before, SF).collect()
    assert sum(r.length for r in packed) == sum(len(encode(t)) + 1 for t in kept["pii"].values())


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 100
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "near_dedup", "decontamination", "pii", "packing"]
    assert pii.PATTERN


def test_decontaminated_both_ways(spark):
    docs, items = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    small, large = (sorted(r.doc_id for r in decontaminate.decontaminated(docs, items, 10, b).collect()) for b in (1 << 20, 0))
    assert small == large and 0 < len(small) < docs.count()

import corpus_pipeline
from bitextspark.llm import langid_crf, quality_rules, tokens

SF = "/root/testdata/sf0.001"


def shingles(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


def plain_kept(rows):
    """Smallest ids of the groups by brute force: five-word shingles with a Jaccard index of 0.8 at least."""
    sets = [shingles(t) for _, t in rows]
    up = list(range(len(rows)))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                up[top(i)] = top(j)
    least = {}
    for i, (doc, _) in enumerate(rows):
        least[top(i)] = min(doc, least.get(top(i), doc))
    return set(least.values())


def test_stages_equal_brute_force_on_their_input(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language_id", "quality_rules", "near_dedup", "packing"]
    one = stages["language_id"](spark, docs, SF)
    labelled = {r["doc_id"]: r for r in langid_crf.predict(docs).collect()}
    assert {r["doc_id"] for r in one.collect()} == {i for i, r in labelled.items() if r["lang_pred"] != "und" and r["score"] >= 0.5}
    two = stages["quality_rules"](spark, one, SF)
    assert {r["doc_id"] for r in two.collect()} == {r["doc_id"] for r in quality_rules.verdicts(one).filter("kept").collect()}
    three = stages["near_dedup"](spark, two, SF)
    rows = [(r["doc_id"], r["text"]) for r in two.collect()]
    kept = {r["doc_id"] for r in three.collect()}
    assert kept == plain_kept(rows)
    # nothing else may go than what is alike, and what is much alike goes
    sets = {i: shingles(t) for i, t in rows}
    alike = lambda a, b: len(sets[a] & sets[b]) / max(1, len(sets[a] | sets[b]))
    assert all(any(alike(i, j) >= 0.8 for j in sets if j != i) for i in sets if i not in kept)
    assert all(alike(i, j) < 0.8 for i in kept for j in kept if i < j)
    assert one.columns == two.columns == three.columns == docs.columns
    four = stages["packing"](spark, three, SF).collect()
    library = tokens.load(tokens.default_path())
    assert sum(r["length"] for r in four) == sum(len(library.encode(r["text"], add_special_tokens=False).ids) + 1 for r in three.collect())
    whole = corpus_pipeline.run(spark, SF).collect()
    assert sorted(map(tuple, whole)) == sorted(map(tuple, four))


def test_clean_documents_pass_the_filters(spark):
    d = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    clean = docs.join(spark.read.parquet(f"{d}/labels.parquet").filter("quality = 1"), "doc_id", "left_semi").filter("size(split(text, ' ')) >= 60")
    kept = corpus_pipeline.quality(spark, corpus_pipeline.language_id(spark, docs, d), d)
    assert clean.join(kept, "doc_id", "left_semi").count() > 0.98 * clean.count()


def test_empty_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs_or_pieces = stage(spark, docs, SF)
        assert docs_or_pieces.count() == 0

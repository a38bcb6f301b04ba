import corpus_pipeline as C
from bedvoids.llm.store import store, table
from tests.llm.test_minhash_dedup import shingles
from tests.llm.test_suffix_dedup import brute


def test_stages_keep_and_drop_what_they_should(spark, sf):
    docs = table(spark, sf, "documents")
    kept = {}
    for name, stage in C.STAGES:
        before = docs
        docs = store(stage(spark, docs, sf), f"test-{name}")
        kept[name] = docs
        if name != C.STAGES[-1][0]:
            assert docs.columns == before.columns
        ids = {r.doc_id for r in docs.select("doc_id").collect()}
        assert ids <= {r.doc_id for r in before.select("doc_id").collect()}
    rows = {r.doc_id: r.text for r in kept["minhash_dedup"].select("doc_id", "text").collect()}
    sets = sorted((shingles(t, 5) for t in rows.values()), key=len)
    for i, a in enumerate(sets):
        for b in sets[i + 1 :]:
            if len(b) * 8 > len(a) * 10:
                break
            assert not a or 100 * len(a & b) < 80 * len(a | b)
    left = {r.doc_id: r.text for r in kept["suffix_dedup"].select("doc_id", "text").collect()}
    assert left.keys() == rows.keys()
    for doc_id, n_bytes, n_removed, n_spans, _ in brute(sorted(rows.items())):
        gone = n_bytes - len(left[doc_id].encode())
        assert n_removed - 6 * n_spans <= gone <= n_removed
    mixed = kept["mixing"]
    assert set(mixed.columns) == {*docs.columns} and mixed.where("mix_copy not in (1, 2)").isEmpty()
    again = C.run(spark, sf)
    key = lambda df: sorted((r.doc_id, r.mix_copy, r.text) for r in df.collect())
    assert key(again) == key(mixed)

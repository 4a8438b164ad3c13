"""Documents that are a benchmark item cut short."""

from conflate.llm import decontam


def test_cut_items_equal_brute_force(spark, docs_of):
    texts = {n: [f"w{n}x{i}" for i in range(n)] for n in (33, 60)}
    bench = spark.createDataFrame([(n, " ".join(w)) for n, w in texts.items()], "item_id long, text string")
    cuts = [(n, k) for n in texts for k in range(int(0.7 * n), n + 1)]
    got = {(r.doc_id, r.item_id) for r in decontam.matches(docs_of([(100 * n + k, " ".join(texts[n][:k])) for n, k in cuts]), bench).collect()}
    assert got == {(100 * n + k, n) for n, k in cuts if (k - 4) / (n - 4) >= 0.8}

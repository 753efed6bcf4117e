"""The document products count terms of every frequency."""

from collections import Counter

from semimul.queries import QUERIES


def test_frequent_terms_are_counted(spark, tmp_path):
    texts = {d: "the The word" + " odd" * (d % 3) + f" only{'abc'[d % 3]}" for d in range(30)}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(d, d % 2) for d in range(30)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    bags = {d: Counter(t.lower().split()) for d, t in texts.items()}
    want = {(i, j): sum(n * bags[j][w] for w, n in bags[i].items()) for i in bags for j in bags}
    assert {(r.i, r.j): r.v for r in QUERIES["outer_terms"](spark, str(tmp_path)).collect()} == want
    got = {r.col: r.v for r in QUERIES["label_vector_terms"](spark, str(tmp_path)).collect()}
    assert got == {j: sum(want[i, j] for i in bags if i % 2) for j in bags}

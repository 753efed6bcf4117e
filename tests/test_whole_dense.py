"""The dense products and the Kronecker product take in every row."""

from semimul.queries import QUERIES


def test_dense_and_kron_have_no_id_filter(spark, tmp_path):
    vectors = {x: [x % 7 - 3.0, 0.5] for x in range(0, 260, 2)}
    spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    spark.createDataFrame([(x, x % 5) for x in range(25)], "n_nationkey long, n_regionkey long").write.parquet(f"{tmp_path}/nation.parquet")
    spark.createDataFrame([(x, "r" * (x + 3)) for x in range(5)], "r_regionkey long, r_name string").write.parquet(f"{tmp_path}/region.parquet")
    d, n = str(tmp_path), len(vectors)
    assert tuple(QUERIES["dense_worst_case_all"](spark, d).first()) == (2 * n * n, n * n, 2000)
    got = {(r.i, r.j): r.v for r in QUERIES["dense_vectors_all"](spark, d).collect()}
    assert got == {(i, j): round(1e6 * sum(x * y for x, y in zip(vectors[i], vectors[j]))) for i in vectors for j in vectors}
    assert QUERIES["kron_tables"](spark, d).count() == 125

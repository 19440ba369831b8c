"""The recall queries search and index every row."""

from oracle import difference

from qacurate.queries import REGISTRY


def test_every_row_is_an_item(spark, sf):
    assert difference(REGISTRY.queries["topk_every_row"](spark, sf), REGISTRY.oracles["topk_every_row"], sf) == ""
    n = spark.read.parquet(f"{sf}/embeddings.parquet").where("vec_id % 50 = 0").count()
    for name in ("topk_lsh_recall", "topk_ivf_recall"):
        got = REGISTRY.queries[name](spark, sf).first()
        assert got.n_true == 5 * n and got.recall >= 0.5

"""The network of embeddings at any size."""

import numpy as np
from pyspark.sql import functions as F

from routefront.sources import networks as N


def test_every_vector_has_neighbours_at_any_size(spark, tmp_path):
    r = np.random.default_rng(7)
    x = r.integers(0, 4, (5100, 6)).astype(np.float32)  # many ties, some equal vectors
    label = r.integers(0, 3, len(x))
    spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(zip(x.tolist(), label.tolist()))], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {}
    for e in N.vector_knn(spark, str(tmp_path)).collect():
        got.setdefault(e["src"], []).append((e["c_l2"], e["dst"], e["c_change"], e["c_hop"]))
    assert len(got) == len(x)
    for i in range(0, len(x), 17):
        d = np.floor(np.sqrt(((x.astype(float) - x[i]) ** 2).sum(1)) * 10000 + 0.5).astype(int)
        best = [j for j in np.lexsort((np.arange(len(x)), d)).tolist() if j != i][:6]
        assert sorted(got[i]) == [(d[j], j, int(label[i] != label[j]), 1) for j in best]


def test_blocks_do_not_change_the_network(spark, tiny):
    rows = lambda df: sorted(map(tuple, df.select("src", "dst", "c_l2", "c_change", "c_hop").collect()))
    v = N.table(spark, tiny, "embeddings")
    a, b = v.toDF("src", "ea", "la"), v.toDF("dst", "eb", "lb")
    square = F.aggregate(F.zip_with("ea", "eb", lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    d = a.crossJoin(b).where("src <> dst").select("src", "dst", F.round(F.sqrt(square) * 10000).cast("long").alias("c_l2"), (F.col("la") != F.col("lb")).cast("long").alias("c_change"), F.lit(1).cast("long").alias("c_hop"))
    d.createOrReplaceTempView("all_pairs")
    want = rows(spark.sql("SELECT src, dst, c_l2, c_change, c_hop FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY c_l2, dst) AS r FROM all_pairs) WHERE r <= 6"))
    assert rows(N.vector_knn(spark, tiny)) == want and rows(N.vector_knn(spark, tiny, block=60)) == want

"""Studies see all rows of their tables."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from pathlift.plans import studies


def test_grouped_models_fit_and_score_all_rows(spark, monkeypatch):
    rows = spark.range(130_000).select(F.col("id").alias("o_orderkey"), (F.pmod(F.xxhash64("id", F.lit(7)), F.lit(100)) < 40 + F.col("id") % 20).cast("int").alias("y"))
    rows = rows.select("*", (F.col("o_orderkey") % 20).alias("segment"), F.when(F.col("o_orderkey") % 3 > 0, F.col("o_orderkey") % 3).alias("region"), F.lit("x").alias("supplier_region"), F.lit(None).cast("string").alias("returnflag"))
    monkeypatch.setattr(studies, "region_base", lambda repo: rows)
    got = {r["feature"]: (r["accuracy"], r["base"]) for r in studies.grouped_models(spark, "").collect()}
    all_rows = rows.withColumn("train", F.pmod(F.xxhash64("o_orderkey"), F.lit(10)) < 7).toPandas()
    asked = all_rows[~all_rows["train"]]
    for feature in ("segment", "region", "supplier_region", "returnflag"):
        bins = all_rows[feature].astype(str)
        known = all_rows["y"][all_rows["train"]]
        sums = known.groupby(bins[all_rows["train"]]).agg(["sum", "count"])
        said = bins[~all_rows["train"]].map((sums["sum"] + 5 * known.mean()) / (sums["count"] + 5)) >= 0.5
        share = asked["y"].mean()
        assert np.allclose(got[feature], ((said.astype(int) == asked["y"]).mean(), max(share, 1 - share)), rtol=0, atol=1e-12)


def test_fi_study_sees_all_vectors(spark, tmp_path):
    rng = np.random.default_rng(3)
    n = 620
    pd.DataFrame({"vec_id": np.arange(n), "embedding": [v.tolist() for v in rng.normal(size=(n, 4))], "label": np.arange(n) % 3}).to_parquet(tmp_path / "embeddings.parquet")
    got = studies.fi_study(spark, str(tmp_path)).collect()
    assert len(got) == 18 and all(r["unknown"] == n - 3 * r["per_cluster"] for r in got)

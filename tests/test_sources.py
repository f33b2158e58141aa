import numpy as np

from proxrec.operators import surface
from proxrec.operators.model import ModelSpec, fit
from proxrec.sources.files import PlantedRatings, export_lists, read_ratings, write_partitioned


def test_formats_agree(spark, tmp_path):
    rows = spark.createDataFrame([(1, 2, 3.0), (1, 3, 4.0), (2, 2, 5.0)], "user_id long, item_id long, rating double")
    want = sorted(map(tuple, rows.collect()))
    for fmt in ("csv", "json", "orc", "parquet"):
        rows.write.format(fmt).option("header", True).save(str(tmp_path / fmt))
        assert sorted(map(tuple, read_ratings(spark, str(tmp_path / fmt), fmt).collect())) == want
    (tmp_path / "r.dat").write_text("1::2::3::0\n1::3::4::0\n2::2::5::0\n")
    assert sorted(map(tuple, read_ratings(spark, str(tmp_path / "r.dat"), "colons").collect())) == want
    write_partitioned(rows, str(tmp_path / "p"), "user_id")
    write_partitioned(rows.where("user_id = 1"), str(tmp_path / "p"), "user_id")
    assert spark.read.parquet(str(tmp_path / "p")).count() == 3


def test_planted_factors_are_found_and_sql_surface(spark, tmp_path):
    spark.dataSource.register(PlantedRatings)
    ratings = spark.read.format("planted_ratings").option("users", 80).option("items", 20).load()
    fitted = fit(ratings, ModelSpec("cosine", 1.0, 4))
    assert fitted.values[2] > 50 * fitted.values[3]
    sides = np.abs(np.random.default_rng(1).standard_normal((20, 3)))
    q = np.linalg.qr(sides)[0]
    assert np.abs(fitted.truncated(3).phi() - q @ q.T).max() < 0.05
    some = ratings.where("(user_id + item_id) % 3 > 0")
    surface.register(spark, fitted, some, 3)
    assert spark.sql("SELECT count(*) AS n FROM recs WHERE rank <= 3").first()["n"] == 240
    assert spark.sql("SELECT max(abs(vec_dot(v, v))) AS x FROM latent").first()["x"] <= 1 + 1e-9
    export_lists(spark.table("recs"), str(tmp_path / "lists"))
    assert spark.read.json(str(tmp_path / "lists")).count() == 80

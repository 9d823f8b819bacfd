import numpy as np
import pytest

from vecengine.sources import io, vecfile


@pytest.mark.parametrize("kind", ["float", "int", "byte"])
def test_vector_files_come_back_in_ranges(spark, tmp_path, kind):
    x = np.arange(70).reshape(10, 7)
    path = str(tmp_path / "x.vecs")
    vecfile.write_vecfile(x, path, kind)
    spark.dataSource.register(vecfile.VecFile)
    df = spark.read.format("vecfile").option("path", path).option("kind", kind).option("rows", 4).load()
    assert df.rdd.getNumPartitions() == 3
    assert [r["vec"] for r in df.orderBy("id").collect()] == x.astype(float).tolist()


def test_index_refuses_another_model_version(spark, tmp_path):
    df = spark.createDataFrame([(1, 0), (2, 1)], "id long, cell int")
    io.save_index(df, str(tmp_path / "i"), version=4)
    assert io.load_index(spark, str(tmp_path / "i"), 4).where("cell = 1").count() == 1
    with pytest.raises(ValueError, match="version"):
        io.load_index(spark, str(tmp_path / "i"), 5)

"""Every registered query of the library against its SQL twin, on the smallest tables."""

import duckdb
import pytest

from rasterflow import workloads

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, float):
        return None if v != v else float(f"{v:.10g}") + 0.0
    if hasattr(v, "tolist"):
        v = v.tolist()
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(workloads.ORACLES))
def test_twin(name, spark, duck):
    df = workloads.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    result = duck.execute(workloads.ORACLES[name])
    names = [d[0] for d in result.description]
    assert sorted(names) == columns
    want = sorted((tuple(plain(r[names.index(c)]) for c in columns) for r in result.fetchall()), key=repr)
    assert got == want


def test_pruning(spark, tmp_path):
    """Choosing a format prunes partitions and columns; a filter reaches the scan."""
    from rasterflow.operators import inference
    from rasterflow.sources import renditions
    from rasterflow.sources.rasters import text_blobs

    renditions.write(inference.renditions(text_blobs(spark, SF)), str(tmp_path / "r"))
    plan = renditions.read(spark, str(tmp_path / "r"), "half_png", ["raster_id"])._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(format_id" in plan and "payload" not in plan.split("ReadSchema")[-1]

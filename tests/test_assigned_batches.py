"""Kernels of the inverted file hold bounded blocks, however many lists a query visits."""

import numpy as np
import pyarrow as pa

from proxigraph.operators import exact, inverted
from proxigraph.operators.model import PointSet, to_lists


def test_batches_stay_small(spark, monkeypatch):
    x = np.random.default_rng(2).normal(size=(400, 8))
    points = PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"))
    cells = inverted.first_centroids(points, 300)
    kept = {}
    monkeypatch.setattr(inverted, "map_arrow", lambda df, run, schema: kept.update(run=run))
    inverted.assign(points, cells, 300)
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(400)), to_lists(x)], ["id", "vec"])
    sizes = [b.num_rows for b in kept["run"](iter([batch]))]
    assert sum(sizes) == 400 * 300 and max(sizes) <= 2048  # 120,000 vectors in one batch before


def test_a_list_is_met_in_blocks(spark, monkeypatch):
    x = np.random.default_rng(2).normal(size=(9000, 4))
    points = PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[:200])], "id long, vec array<double>"))
    made = inverted.InvertedIndex.build(points, 1, 1)
    kept, held = {}, []
    monkeypatch.setattr(inverted.resident, "answer", lambda q, rows, folder, columns, cells, load, ask, schema: kept.update(ask=ask))
    close = exact.close_pairs
    monkeypatch.setattr(exact, "close_pairs", lambda q, x, *more: held.append(len(q) * len(x)) or close(q, x, *more))
    made._met(made.probed(points, 1), 3, None)
    out = kept["ask"]((np.arange(9000), x), pa.table({"id": np.arange(1024), "vec": to_lists(x[:1024])}))
    assert held and max(held) <= exact.QUERY_BLOCK * exact.POINT_BLOCK
    assert [v[0] for v in out.column(1).to_pylist()] == list(range(1024))

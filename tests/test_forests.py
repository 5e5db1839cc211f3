"""Union-find over many batches."""

import numpy as np
import pyarrow as pa

from blockgraph.operators import algorithms as alg


def test_the_forest_is_not_sorted_again_for_every_batch(monkeypatch):
    src = np.random.default_rng(1).permutation(400_000) + 1
    dst = np.where(src % 1000, src - 1, src)
    seen, forest = [], alg.forest
    monkeypatch.setattr(alg, "forest", lambda a, b: seen.append(len(a)) or forest(a, b))
    monkeypatch.setattr(alg, "FOLD_ROWS", 10_000, raising=False)
    batches = (pa.RecordBatch.from_arrays([pa.array(src[i : i + 4_000]), pa.array(dst[i : i + 4_000])], ["src", "dst"]) for i in range(0, len(src), 4_000))
    got = {s: d for b in alg._forests(batches) for s, d in zip(b.column("src").to_pylist(), b.column("dst").to_pylist(), strict=True)}
    assert all(got.get(v, v) == v // 1000 * 1000 for v in range(1, 400_001)) and sum(seen) < 4 * len(src)

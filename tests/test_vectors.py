import os

import numpy as np
import pyarrow.parquet as pq
import pytest

from graphkw.sources.tables import VECTOR, vectors
from graphkw.schema import TAG

SMALL = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the given tables")


@pytest.mark.parametrize("block", [2000, 97])
def test_vectors_point_to_their_true_nearest(spark, block):
    t = pq.read_table(f"{SMALL}/embeddings.parquet")
    ids = t["vec_id"].to_numpy()
    e = np.array(t["embedding"].to_pylist(), float)
    e /= np.linalg.norm(e, axis=1)[:, None]
    c = np.round(e @ e.T, 12)
    np.fill_diagonal(c, -np.inf)
    want = {(int(ids[i]), int(ids[j])) for i in range(len(ids)) for j in np.lexsort((ids, -c[i]))[:5]}
    got = {(r.src - VECTOR * TAG, r.dst - VECTOR * TAG) for r in vectors(spark, SMALL, block=block).edges.collect()}
    assert got == want

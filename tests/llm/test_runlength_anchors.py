"""Anchors of byte windows: a phrase shorter than one is shared by nobody; results stay those of a plain search."""

import numpy as np
import pyarrow as pa

from pathload.llm.common import text_buffer
from pathload.llm.runlength import ByteRepeats, RunLengthIndex


def test_short_common_phrases_are_no_anchors():
    rng = np.random.default_rng(5)
    phrase = b"seventeen bytes!!"
    texts = [bytes(rng.integers(97, 123, 40).tolist()) + phrase + bytes(rng.integers(97, 123, 40).tolist()) for _ in range(300)]
    kind = ByteRepeats()
    seen = [set(kind.anchors(*text_buffer(pa.chunked_array([pa.array([t.decode()])]))).tolist()) for t in texts]
    assert all(seen) and len(set.union(*seen)) == sum(map(len, seen))


def test_streamed_classes_equal_plain_ones():
    rng = np.random.default_rng(6)
    base = rng.integers(97, 99, 90).astype(np.uint8)
    block = np.stack([np.roll(base, int(i)) for i in rng.integers(0, 30, 40)])
    size = rng.integers(50, 77, 40)
    ids = rng.integers(0, 9, 40)
    got = RunLengthIndex(block[:, :76], size).least_ids(ids)
    least = {}
    for i, n in enumerate(size):
        for o in range(n - 49):
            w = block[i, o : o + 50].tobytes()
            least[w] = min(least.get(w, 99), ids[i])
    for i, n in enumerate(size):
        for o in range(n - 49):
            assert got[i, o] == least[block[i, o : o + 50].tobytes()]

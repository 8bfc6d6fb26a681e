"""What a Python worker holds: workers serve one stage after another, within one executor's memory."""

import tracemalloc

import numpy as np
import pyarrow as pa
from cellstream.llm import common, jaccard


def _batches(rng, rows, words):
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 30, words)).encode() for _ in range(rows)]
    return texts, [pa.RecordBatch.from_arrays([pa.array(texts[k : k + 50], pa.binary())], ["raw"]) for k in range(0, rows, 50)]


def _counts(found):
    out = {}
    for b in found:
        for h, c in zip(*(x.to_pylist() for x in b.columns), strict=True):
            out[h] = out.get(h, 0) + c
    return out


def test_tally_counts_and_holds_one_buffer():
    texts, batches = _batches(np.random.default_rng(3), 300, 60)
    every = np.concatenate([jaccard._hashes(t.split(), 1) for t in texts])
    h, c = np.unique(every, return_counts=True)
    want = dict(zip(h.view(np.int64).tolist(), c.tolist(), strict=True))
    assert _counts(jaccard._tally(1, 1, 10**6)(batches)) == want
    assert _counts(jaccard._tally(1, 1, 97)(batches)) == want
    assert _counts(jaccard._tally(1, 250, 10**6)(batches)) == {k: v for k, v in want.items() if v >= 250}
    assert _counts(jaccard._tally(1, 10**4, 10**6)(batches)) == {} == _counts(jaccard._tally(1, 16, 97)([]))
    room = 1 << 20
    _, batches = _batches(np.random.default_rng(4), 50, 25_000)
    tracemalloc.start()
    assert sum(len(b) for b in jaccard._tally(5, 16, room)(batches)) < room
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    # Sorting copies of the whole would take the buffer's size several times.
    assert peak < 2.5 * 8 * room


def test_near_duplicates_leave_no_encoder_beside_them():
    common._ENCODERS[("other stage",)] = object()
    list(jaccard._tally(5, 16, 1000)(_batches(np.random.default_rng(5), 10, 20)[1]))
    assert not common._ENCODERS

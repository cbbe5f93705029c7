"""What a Python worker holds while it tokenizes, and what it keeps afterwards."""

import gc
import tracemalloc

import numpy as np
import pyarrow as pa
from treefold.llm import common, tokens


def test_slice_of_a_batch_is_small():
    words = ["the", "river", "and", "a", "stone", "12", "(old)", "winter's"]
    texts = [" ".join(words[(i + j) % len(words)] for j in range(400)) for i in range(4000)]
    batch = pa.record_batch({"doc_id": pa.array(range(len(texts))), "text": pa.array(texts), "chars": pa.array([len(t) for t in texts])})
    list(tokens.encoded_slices([batch.slice(0, 10)], None))
    tracemalloc.start()
    try:
        found = sum(len(x) for _, ids in tokens.encoded_slices([batch], None) for x in ids)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert found > len(texts) * 400
    assert peak < 60_000_000, peak


def test_worker_gives_back():
    def resident():
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * 4096

    def run(batches):
        held = [bytes(1000) + b"x" for _ in range(200_000)]
        pins = held[::40]
        del held
        yield np.int64(len(pins))

    before = resident()
    assert list(common.freed(run)(iter([]))) == [5000]
    gc.collect()
    assert resident() - before < 60_000_000


def test_pieces_are_forgotten():
    tokens.tokenizer().encode(["some words to know"])
    assert tokens.tokenizer().codes
    tokens.forget_pieces()
    assert not tokens.tokenizer().codes
    assert [x.tolist() for x in tokens.tokenizer().encode(["some words to know"])] == [x.tolist() for x in tokens.WordTokenizer().encode(["some words to know"])]

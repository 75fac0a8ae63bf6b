import random

import numpy as np
import pyarrow as pa
import pytest

from kmerspark.llm import _blocks as m
from kmerspark.llm._blocks import Blocks, Space, by_block, read_payload, repeated, sort_places
from kmerspark.llm._repeats import Block
from kmerspark.llm._text import Rolling, Words, column, gram_hashes


def texts(n, words=120, seed=0):
    rng = random.Random(seed)
    return [(i, " ".join(f"w{rng.getrandbits(40)}" for _ in range(words))) for i in range(n)]


def answers(spark, rows):
    """By block: its grams, and which of them are said to repeat."""
    blocks = Blocks(spark.createDataFrame(rows, "id long, text string").repartition(4))
    found = blocks.with_rows(by_block(blocks.counted(lambda b: Block(b, 50).items()))).collect()
    out = []
    for r in found:
        items = Block(read_payload(r.payload), 50).items()
        out.append((items, repeated(blocks.space, items, [p.asDict() for p in r.parts])))
    return blocks.space, out


@pytest.mark.parametrize("scale", [1, 100])
def test_cells_hit_by_chance_stay_few_at_any_size(spark, monkeypatch, scale):
    """The space follows the input: 100 times as much text, the same share of chance hits."""
    monkeypatch.setattr(m, "BLOCK_BYTES", 40_000)
    _, found = answers(spark, texts(12 * scale))
    items, hit = (np.concatenate(x) for x in zip(*found, strict=True))
    assert len(np.unique(items)) == len(items) == 12 * scale * 96
    assert hit.mean() < 0.05


def test_repeats_are_always_found(spark, monkeypatch):
    monkeypatch.setattr(m, "BLOCK_BYTES", 2000)
    rows = texts(40)
    rows += [(100 + i, rows[i][1]) for i in range(10)] + [(200, rows[0][1] + " " + rows[0][1])]
    space, found = answers(spark, rows)
    items = np.concatenate([f[0] for f in found])
    kept, count = np.unique(items, return_counts=True)
    again = set(kept[count > 1].tolist())
    for own, hit in found:
        assert all(h for x, h in zip(own.tolist(), hit.tolist(), strict=True) if x in again)


def test_a_space_for_any_size():
    for n, parts in ((0, 1), (10**6, 8), (10**10, 200), (10**14, 100_000)):
        s = Space.of(n, parts)
        assert 2**s.bits >= 4 * n or s.bits - s.range_bits == 31
        assert 0 < s.bits - s.range_bits <= 31 and s.bits <= 64
    assert Space.of(10**14, 100_000).bits >= 48


def test_counts_round_trip():
    for count in ([1] * 9, [1, 2, 1, 254, 255, 256, 10**6, 1], [3], [1, 300]):
        assert (1 + m.decode_more(m.encode_counts(np.array(count)), len(count))).tolist() == count


def test_sorting_keeps_places():
    x = np.random.default_rng(0).integers(0, 50, 1000).astype(np.uint64)
    for bits in (6, 60):
        got, order = sort_places(x, bits)
        assert got.tolist() == sorted(x.tolist()) and order.tolist() == np.argsort(x, kind="stable").tolist()


def test_rolling_hashes_tell_runs_apart():
    words = np.random.default_rng(0).integers(0, 2**63, 500).astype(np.uint64)
    words[300:350] = words[100:150]
    r = Rolling(words)
    grams = r.windows(25)
    assert grams[100] == grams[300] and len(np.unique(grams)) == len(grams) - 26 and len(gram_hashes(words, 25)) == len(grams)
    a = np.array([100, 300, 100, 300])
    one = r.runs(a, a + np.array([40, 40, 41, 51]))
    assert one[0] == one[1] and len(set(one.tolist())) == 3
    assert Rolling(words[100:150]).runs(np.array([0]), np.array([40]))[0] == one[0]


def test_spaced_words():
    w = Words(pa.array(["a bc", None, "", " déf\n", "x"]))
    assert w.spaced().tobytes().decode() == "a bc déf x " and column(pa.record_batch({"t": ["q"]}), "t").to_pylist() == ["q"]

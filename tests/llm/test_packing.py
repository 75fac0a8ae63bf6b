import zlib
from functools import lru_cache

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from kmerspark.llm.packing import encode_block, harmonic_packing, pack_lengths

tokenizers = pytest.importorskip("public_tokenizers")
PATH = tokenizers.path("word_bpe_49k.json")


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 300), max_size=60), st.sampled_from([8, 64, 128]), st.integers(1, 9))
def test_every_unit_once_and_no_padding(lengths, capacity, classes):
    p = pack_lengths(np.array(lengths, dtype=np.int64), capacity, classes)
    seen = [np.zeros(n, int) for n in lengths]
    fill = {}
    for d, s, n, q, o in zip(*(p[k].tolist() for k in ("doc", "start", "length", "sequence", "offset")), strict=True):
        assert n > 0
        seen[d][s : s + n] += 1
        fill.setdefault(q, []).append((o, n))
    assert all((x == 1).all() for x in seen)
    for pieces in fill.values():
        at = 0
        for o, n in sorted(pieces):
            assert o == at
            at += n
        assert at == capacity or at & (at - 1) == 0 and at < capacity


def test_a_kept_bin_holds_the_fixed_count():
    p = pack_lengths(np.array([700] * 4 + [5] * 400), 2048, 8)  # class 2: two in a bin
    of_class = p["doc"] < 4
    assert sorted(np.bincount(p["sequence"][of_class]).tolist()).count(2) == 2


def test_ids_are_the_tokenizer_s():
    import pyarrow as pa
    from tokenizers import Tokenizer

    texts = ["Hello  World's\x0bünïx 42!", "", None, "a<|endoftext|>b  x\u0085y Straße ΑΣ", "é é e ́"]
    ids, lengths = encode_block(pa.array(texts), PATH)
    t = Tokenizer.from_file(PATH)
    want = [t.encode(x or "", add_special_tokens=False).ids + [1] for x in texts]
    assert lengths.tolist() == [len(w) for w in want]
    assert ids.tolist() == sum(want, [])


@lru_cache
def plain_tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(PATH)


PARTS = ["a", "Zé", "s", "'s", "'LL", "'", "12", "½", "٣", ".", "...", "…", "́", "ß", "Σ", "σ", "<|endoftext|>", "<|ENDOFTEXT|>", "<|", "中", " ", "\n", "\u00a0", "\u0085", "\u3000", "≠", "@x_y"]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.lists(st.sampled_from(PARTS), max_size=12).map("".join), min_size=1, max_size=4))
def test_ids_of_any_text(texts):
    import pyarrow as pa

    t = plain_tokenizer()
    assert encode_block(pa.array(texts), PATH)[0].tolist() == sum([t.encode(x, add_special_tokens=False).ids + [1] for x in texts], [])


def test_rows(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(PATH)
    rows = [(1, "word " * 5000, "x"), (2, None, "y"), (3, "", "z"), (None, "lost id", None), (2, "again", "y")]
    got = harmonic_packing(spark.createDataFrame(rows, "doc_id long, text string, offset string").repartition(2), PATH).toPandas()
    assert set(got.doc_tokens[got.doc_id == 1]) == {5001}
    ids = np.array(t.encode(rows[0][1], add_special_tokens=False).ids + [1], "<u4")
    one = got[got.doc_id == 1]
    for r in one.itertuples():
        assert zlib.crc32(ids[r.start : r.start + r.length].tobytes()) == r.ids_crc32
    assert one.length.sum() == 5001
    assert harmonic_packing(spark.createDataFrame([], "doc_id long, text string"), PATH).count() == 0

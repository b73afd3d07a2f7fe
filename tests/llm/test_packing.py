import os

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hypernear.llm import packing

pytestmark = pytest.mark.skipif(not os.path.exists(packing.VOCABULARY), reason="no vocabulary")


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 50), max_size=120))
def test_best_fit_decreasing(lengths):
    rows = packing.pack(lengths, 50)
    assert sorted(p for r in rows for p in r) == list(range(len(lengths)))
    assert all(sum(lengths[p] for p in r) <= 50 for r in rows)
    # The same as choosing the fullest row that fits by looking at all of them.
    room: list[int] = []
    for n in sorted(lengths, reverse=True):
        fits = [r for r in room if r >= n]
        if fits:
            room[room.index(min(fits))] -= n
        else:
            room.append(50 - n)
    assert len(room) == len(rows) and sorted(room) == sorted(50 - sum(lengths[p] for p in r) for r in rows)


def test_round_trip_and_edge_cases(documents, no_documents):
    packed = packing.pack_tokens(documents, width=512, block_tokens=20_000)
    encode = packing.tokenizer(packing.load_ranks(packing.VOCABULARY))
    back: dict = {}
    for r in packing.unpack(packed).collect():
        back.setdefault(r.doc_id, {}).setdefault(r.piece, []).append(r.ids)
    for row in documents.select("doc_id", "text").distinct().collect():
        if not row.text:
            assert row.doc_id not in back
            continue
        pieces = back[row.doc_id]
        copies = {len(p) for p in pieces.values()}
        assert copies == {2 if row.doc_id == 2 else 1}
        assert [i for k in sorted(pieces) for i in pieces[k][0]] == encode(row.text)
    for r in packed.collect():
        assert r.n_tokens == r.cu_seqlens[-1] == len(r.ids) // 2 <= 512
        assert r.position_resets == r.cu_seqlens[:-1]
        positions = packing.position_ids(r.cu_seqlens)
        assert len(positions) == r.n_tokens and all(positions[p] == 0 for p in r.position_resets)
        assert (np.diff(positions)[np.diff(positions) != 1] <= 0).all()
    assert packing.pack_tokens(no_documents).count() == 0


def test_matrices_are_written(documents, tmp_path):
    packed = packing.pack_tokens(documents, width=256)
    written = packing.write_matrices(packed, str(tmp_path / "out"), 256)
    assert written.count() == packed.count()
    matrix = np.stack([np.frombuffer(r.ids, "<u2") for r in written.orderBy("block", "row").collect()])
    assert matrix.shape == (packed.count(), 256)
    for line, r in zip(matrix, packed.orderBy("block", "row").collect()):
        assert line[: r.n_tokens].tobytes() == bytes(r.ids) and not line[r.n_tokens :].any()

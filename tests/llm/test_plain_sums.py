"""The lattice without logarithms, and with the lookups of prefixes, against the recursion in logarithms."""

import numpy as np
import pytest

from rankgrid.llm import lattice_lm

WORDS = [b"a", b"abra", b"cadabra", "größe".encode(), b"x" * 400, b"the", b"internationalisation"]


@pytest.fixture(scope="module")
def pieces():
    import public_tokenizers

    return lattice_lm.existing_pieces(public_tokenizers.path("piece_bpe_32k.model"))


def test_sums_without_logarithms_are_the_same(pieces, monkeypatch):
    plain = lattice_lm.Lattice(pieces)
    p, e = plain.log_probability(WORDS), plain.expected(WORDS)
    # a very long word would be less than the least number
    assert {r for rows, *_, linear in plain._by_size(WORDS) if not linear for r in rows.tolist()} == {4}
    monkeypatch.setattr(lattice_lm, "LEAST_LOG", 1.0)
    assert not any(linear for *_, linear in plain._by_size(WORDS))
    assert np.allclose(p, plain.log_probability(WORDS), rtol=1e-12)
    assert np.allclose(e, plain.expected(WORDS), rtol=1e-9, atol=1e-12)


def test_prefixes_lose_no_piece(pieces):
    bare = lattice_lm.Pieces(pieces.hashes, pieces.starting, pieces.longest, pieces.log_p)
    got, want = lattice_lm.Lattice(pieces)._arcs(WORDS), lattice_lm.Lattice(bare)._arcs(WORDS)
    assert (got[0] == want[0]).all()
    assert (want[0] >= 0).sum() > len(want[0][0])
    # fewer places are looked up
    looked = []
    for p in (pieces, bare):
        lattice = lattice_lm.Lattice(p)
        find, seen = lattice.index.find, []
        lattice.index.find = lambda h, find=find, seen=seen: (seen.append(len(h)), find(h))[1]
        lattice._arcs(WORDS)
        looked.append(sum(seen))
    assert looked[0] < looked[1] / 3

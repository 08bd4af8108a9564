"""Words that are kept between slices: ids are the library's, samples do not depend on what was met before."""

import random

import pytest

from rpqframe.llm import sp_sampling
from rpqframe.llm.token_count import processor


class Counting:
    """The library, with the characters it was given to encode."""

    def __init__(self):
        self.sp, self.given = processor(sp_sampling.model_file()), 0

    def encode(self, texts, **how):
        self.given += len(texts) if isinstance(texts, str) else sum(map(len, texts))
        return self.sp.encode(texts, **how)

    def normalize(self, texts):
        return self.sp.normalize(texts)


def texts_of(seed, n=300):
    r = random.Random(seed)
    parts = [*"ab xé漢😀\n\t\0　", "▁", "  ", "▁ ", "the ", "ﬁ", "Ａ ", "<s>", "</s>", "<0x0A>", "<unk>", "word "]
    return ["".join(r.choice(parts) for _ in range(r.randint(0, 14))) for _ in range(n)] + ["", " ", "a ", "  a  ", "▁"]


def slice_of(vocab, texts):
    return sp_sampling.Slice(vocab, texts, sp_sampling.row_keys(list(range(len(texts))), 7))


@pytest.mark.parametrize("kept", [0, 2_000, 1 << 20])
def test_ids_and_samples_whatever_is_kept(monkeypatch, kept):
    monkeypatch.setattr(sp_sampling, "KNOWN_EDGES", kept)
    vocab, sp = sp_sampling.Vocabulary(sp_sampling.model_file(), 1.0), Counting()
    for seed in (1, 2, 1, 3):
        texts = texts_of(seed)
        part = slice_of(vocab, texts)
        found, _ = part.top(2)
        got = [[part.pieces(e).tolist() for e, _, _ in f] for f in found]
        if seed != 2:  # words can be kept that have no ids yet
            assert [i.tolist() for i in part.encoded(sp)] == sp.sp.encode(texts)
        alone = slice_of(fresh := sp_sampling.Vocabulary(sp_sampling.model_file(), 1.0), texts)
        assert got == [[alone.pieces(e).tolist() for e, _, _ in f] for f in alone.top(2)[0]] and fresh is not vocab


def test_a_repeated_word_goes_to_the_library_once():
    vocab, sp = sp_sampling.Vocabulary(sp_sampling.model_file(), 1.0), Counting()
    for _ in range(3):
        assert [i.tolist() for i in slice_of(vocab, ["some words again and again"] * 50).encoded(sp)] == sp.sp.encode(["some words again and again"] * 50)
    assert sp.given < 60

"""The report's own encoding and decoding: every text goes to the library whole, whatever words were met before."""

import pyarrow as pa
import xxhash

from rpqframe.llm import sp_sampling
from rpqframe.llm.token_count import processor


class Noting:
    """The library, with the texts it was given and the ids it was given back."""

    def __init__(self):
        self.sp, self.texts, self.ids = processor(sp_sampling.model_file()), [], []

    def encode(self, texts, **how):
        self.texts += [texts] if isinstance(texts, str) else list(texts)
        return self.sp.encode(texts, **how)

    def decode(self, ids, **how):
        self.ids.append(ids)
        return self.sp.decode(ids, **how)

    def __getattr__(self, name):
        return getattr(self.sp, name)


def test_the_report_encodes_whole_texts(monkeypatch):
    noting = Noting()
    vocab = sp_sampling.Vocabulary(sp_sampling.model_file(), 1.0)
    monkeypatch.setattr(sp_sampling, "_slices", lambda docs, id_col, text_col, model_path, alpha, seed, make, schema: make)
    monkeypatch.setattr(sp_sampling, "processor", lambda path: noting)
    make = sp_sampling.sample_report(None)
    texts = ["some words again and again", "again some words", "again some words", "", "  two  blanks ▁ 漢😀"]
    rows = pa.RecordBatch.from_arrays([pa.array(range(len(texts)))], names=["id"])
    for turn in range(2):  # all words are known the second time
        noting.texts, noting.ids = [], []
        out = make(rows, texts, sp_sampling.Slice(vocab, texts, sp_sampling.row_keys(list(range(len(texts))), 7)), vocab).to_pydict()
        assert [t for t in noting.texts if t] == [t for t in texts if t]
        want = [noting.sp.encode(t) for t in texts]
        assert out["n_tokens"] == [len(i) for i in want] and all(out["tokens_decode"])
        assert out["token_hash"] == [xxhash.xxh64_hexdigest(b"".join(x.to_bytes(4, "little") for x in i)) for i in want]
        assert sum(len(i) for i in noting.ids) == sum(len(i) for i in want)

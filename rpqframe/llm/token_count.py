"""Token counts of whole texts with overlap resynchronisation for huge ones.

Texts up to ``chunk_bytes`` go to the library whole. Longer ones are encoded in chunks that
overlap; neighbouring encodings are spliced at a boundary that both have inside their overlap
and that is proven stable: a white-space character that follows another character. No piece
of the vocabulary holds the word-start mark after another character (checked when the model is
loaded), and merges only ever build pieces, so no merge can reach across such a place, whatever
stands on either side. Where an overlap holds no such boundary it is widened, up to the
end of the text, so the count always equals that of the whole text.

Defined results: null counts as empty (no bytes, no tokens); repeated rows stay repeated; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rpqframe.llm.common import pick, text_slices

MARK = "▁"
MODEL = "piece_bpe_32k.model"


def model_file(path: str | None = None) -> str:
    if path:
        return path
    import public_tokenizers

    return public_tokenizers.path(MODEL)


@lru_cache(maxsize=4)
def processor(path: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path)


@lru_cache(maxsize=4)
def splits_before_space(path: str) -> bool:
    """True if no piece holds the word-start mark after another character."""
    sp = processor(path)
    return not any(MARK in sp.id_to_piece(i).lstrip(MARK) for i in range(sp.vocab_size()))


def _spans(sp, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets of the pieces; the pieces of one character that falls back to bytes share theirs."""
    pieces = sp.encode(raw, return_type="proto").pieces
    return np.array([p.begin for p in pieces], dtype=np.int64), np.array([p.end for p in pieces], dtype=np.int64)


_SPACES = (b" ", MARK.encode())


def _stable(raw: bytes, at: int) -> bool:
    return 0 < at < len(raw) and raw.startswith(_SPACES, at) and not raw.endswith(_SPACES, 0, at)


def _whole(raw: bytes, at: int) -> int:
    """The start of the character that holds the byte."""
    while 0 < at < len(raw) and raw[at] & 0xC0 == 0x80:
        at -= 1
    return min(at, len(raw))


def count_long(sp, raw: bytes, chunk: int, overlap: int) -> int:
    """Tokens of the whole text, from encodings of overlapping chunks."""
    total, start, frm = 0, 0, 0  # frm: first offset that is not counted yet
    while True:
        end, wide = _whole(raw, start + chunk), overlap
        while True:
            begins, ends = (x + start for x in _spans(sp, raw[start:end]))
            if end >= len(raw):
                return total + int((begins >= frm).sum())
            nxt = _whole(raw, max(frm, end - wide))
            right = _spans(sp, raw[nxt : _whole(raw, end + overlap)])[0] + nxt
            common = np.intersect1d(begins[(begins > max(nxt, frm)) & (begins < end)], right)
            cut = next((int(p) for p in common[::-1] if _stable(raw, int(p))), None)
            if cut is not None:
                break
            wide, end = wide * 2, _whole(raw, end + wide)
        total += int(((begins >= frm) & (begins < cut)).sum())
        frm, start = cut, nxt


def count_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model_path: str | None = None, limit: int = 4096, chunk_bytes: int = 1 << 17, overlap: int = 512) -> DataFrame:
    """id_col, n_bytes, n_tokens, over_limit; one row per input row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path = model_file(model_path)
        sp = processor(path)
        for batch in batches:
            for rows, texts in text_slices(batch):
                raw = [t or b"" for t in texts]
                counts = [0] * len(raw)
                short = [i for i, r in enumerate(raw) if len(r) <= chunk_bytes]
                for i, ids in zip(short, sp.encode([raw[i] for i in short], num_threads=1) if short else []):
                    counts[i] = len(ids)
                for i, r in enumerate(raw):
                    if len(r) > chunk_bytes:
                        counts[i] = count_long(sp, r, chunk_bytes, overlap) if splits_before_space(path) else len(sp.encode(r))
                yield pa.RecordBatch.from_arrays(
                    [rows.column(0), pa.array([len(r) for r in raw], pa.int64()), pa.array(counts, pa.int64()), pa.array([c > limit for c in counts])],
                    names=["id", "n_bytes", "n_tokens", "over_limit"],
                )

    src = pick(docs, id_col, text_col).toDF("id", "text")
    kind = src.schema["id"].dataType.simpleString()
    return src.mapInArrow(run, f"id {kind}, n_bytes bigint, n_tokens bigint, over_limit boolean").withColumnRenamed("id", id_col)

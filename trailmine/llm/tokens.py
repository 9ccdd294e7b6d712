"""Token ids of whole texts by a public tokenizer, with a memo of its chunks.

``word_bpe_49k.json`` drops white space, and neither its normaliser nor its pre-tokenizer
joins what white space parts; so the ids of a text are those of its chunks between ASCII
white space, one after another. Arrow splits a batch of texts and finds its distinct chunks;
each is encoded by the tokenizers library and kept in a bounded memo of the worker. Chunks of
plain letters, digits and signs go straight to the library's BPE model, since its normaliser
and pre-tokenizer do no more to them than lower-casing and the split below; all others go
through the whole tokenizer.
"""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Chunks that a worker keeps; beyond that its memo starts anew.
MEMO_CHUNKS = 600_000
#: Characters for which the short way is exact: printable ASCII and Latin-1 letters.
SIMPLE = re.compile("[!-~À-ÖØ-öø-ÿ]+")
#: How this tokenizer's pre-tokenizer parts such chunks, once in lower case.
PIECES = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")


def byte_letters() -> list[str]:
    """The letter that byte-level BPE writes for each byte."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    table = {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(rest)}
    return [table[b] for b in range(256)]


class ChunkEncoder(dict):
    """Memo from chunks to their ids, as little-endian unsigned 32-bit numbers."""

    def __init__(self, path: str, keep: int = MEMO_CHUNKS) -> None:
        super().__init__()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.keep, self.pieces = keep, {}
        self.letters = byte_letters()
        self.model = self.tokenizer.model if os.path.basename(path) == "word_bpe_49k.json" else None

    def __missing__(self, chunk: str) -> bytes:
        if self.model is None or not SIMPLE.fullmatch(chunk) or "<|" in chunk:
            ids = np.array(self.tokenizer.encode(chunk, add_special_tokens=False).ids, "<u4").tobytes()
        else:
            ids = b"".join([self.pieces.get(p) or self.piece(p) for p in PIECES.findall(chunk.lower())])
        self[chunk] = ids
        return ids

    def piece(self, piece: str) -> bytes:
        written = piece if piece.isascii() else "".join(self.letters[b] for b in piece.encode())
        ids = np.array([t.id for t in self.model.tokenize(written)], "<u4").tobytes()
        self.pieces[piece] = ids
        return ids

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, and the offsets at which each text's ids begin and end."""
        if len(self) > self.keep:
            self.clear()
            self.pieces.clear()
        parts = pc.ascii_split_whitespace(texts)
        bounds = parts.offsets.to_numpy()
        coded = parts.values.dictionary_encode()
        at = coded.indices.to_numpy()
        found = list(map(self.__getitem__, coded.dictionary.to_pylist()))
        sizes = np.fromiter(map(len, found), np.int64, len(found)) // 4
        flat = np.frombuffer(b"".join(found), "<u4")
        starts = np.cumsum(sizes) - sizes
        lengths = sizes[at]
        upto = np.concatenate([[0], np.cumsum(lengths)])
        ids = flat[np.repeat(starts[at] - upto[:-1], lengths) + np.arange(upto[-1])] if len(at) else flat[:0]
        return ids, upto[bounds]


_LOADED: dict[str, ChunkEncoder] = {}


def encoder(path: str) -> ChunkEncoder:
    """This process's encoder for a file."""
    if path not in _LOADED:
        _LOADED[path] = ChunkEncoder(path)
    return _LOADED[path]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")

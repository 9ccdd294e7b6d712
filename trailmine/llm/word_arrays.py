"""Words of a batch of texts as arrays."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def split_words(texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(distinct words, number of each word in order, bounds of the texts) after lower-casing
    A-Z; words are what ASCII white space parts."""
    parts = pc.ascii_split_whitespace(pc.ascii_lower(texts))
    coded = parts.values.dictionary_encode()
    names, at, bounds = coded.dictionary.to_pylist(), coded.indices.to_numpy(), parts.offsets.to_numpy()
    if "" in names:  # white space at an end of a text leaves an empty part
        real = at != names.index("")
        bounds = np.concatenate([[0], np.cumsum(real)])[bounds]
        at = at[real]
    return names, at, bounds


def sums_by_text(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sum of the values of each text."""
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    return np.bincount(owner, values, len(bounds) - 1)

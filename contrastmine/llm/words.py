"""Words of many texts as numbers, split and numbered in Arrow."""

from __future__ import annotations

import numpy as np


def numbered(texts) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(distinct words, code of each word, bounds of each text in the codes) of lower-cased texts.

    Words are runs of letters and digits."""
    import pyarrow as pa
    import pyarrow.compute as pc

    low = pc.replace_substring_regex(pc.utf8_lower(pa.array(texts, pa.large_string())), r"[^\pL\pN]+", " ")
    parts = pc.utf8_split_whitespace(low)
    coded = parts.values.dictionary_encode()
    names, codes, bounds = coded.dictionary.to_pylist(), coded.indices.to_numpy(), parts.offsets.to_numpy()
    if "" in names:  # a text that begins or ends with white space
        keep = codes != names.index("")
        bounds = np.concatenate(([0], np.cumsum(keep)))[bounds]
        codes = codes[keep]
    return names, codes, bounds


def hashed(names: list[str]) -> np.ndarray:
    """The same 64-bit hash of a word on every machine."""
    import pandas as pd

    return pd.util.hash_array(np.array(names, object), categorize=False) if names else np.zeros(0, np.uint64)


def mixed(h: np.ndarray) -> np.ndarray:
    """Finish a 64-bit hash so that all bits depend on all bits."""
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))

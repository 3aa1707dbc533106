"""Token ids of whole texts from a file of the tokenizers library, one encoding per distinct piece between blanks.

The tokenizer drops white space before it splits words, and no word spans a blank, so a text's ids are those of its
pieces in order. Texts are split and numbered by piece in Arrow; each distinct piece is encoded once per worker and
batch. This is used only for a file whose normaliser and splitter are those stated below; with any other, whole texts go
to the library. Pieces of ASCII and Latin-1 letters, digits and marks, most of any text here, are lower-cased and split as the
library's normaliser and splitter would, and go to its model straight; all others take its whole path. The cache is emptied when it holds `limit`
pieces, which changes the speed only."""

from __future__ import annotations

import json
import os
import re
from array import array

import numpy as np

from .shared import worker_state

# Letters of ASCII and Latin-1, digits and marks, without those that start a contraction or a special token; and its words.
PLAIN = re.compile("[!-&(-;=-~À-ÖØ-öø-ÿ]+")
PARTS = re.compile("[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")

# The normaliser and splitter that the split at blanks and the direct way to the model are right for.
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]}
SPLITTER = {
    "type": "Sequence",
    "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ],
}


def known_form(told: dict) -> bool:
    """Whether a tokenizer file, read as JSON, has that normaliser and splitter, a plain pair model, and no added token that a blank or a plain piece can meet."""
    model = told["model"]
    return told["normalizer"] == NORMALIZER and told["pre_tokenizer"] == SPLITTER and model["type"] == "BPE" and not model.get("dropout") and all(t["content"].startswith("<") and " " not in t["content"] for t in told["added_tokens"])


def byte_letters() -> list[str]:
    """The printable character that byte-level vocabularies write for each byte: itself where printable, else the next free one from 256 on."""
    keeps = lambda b: 33 <= b <= 126 or 161 <= b <= 172 or b >= 174
    spare = iter(range(256, 512))
    return [chr(b) if keeps(b) else chr(next(spare)) for b in range(256)]


class PieceEncoder:
    def __init__(self, path: str, limit: int = 400_000):
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            self.by_piece = known_form(json.load(f))
        self.limit = limit
        self.kind = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.code = "H" if self.kind.itemsize == 2 else "I"
        self.letters = byte_letters()
        self.cache: dict[str, bytes] = {"": b""}

    def _bytes(self, ids) -> bytes:
        return array(self.code, ids).tobytes()

    def _whole(self, piece: str) -> bytes:
        return self._bytes(self.tokenizer.encode(piece, add_special_tokens=False).ids)

    def _word(self, word: str) -> bytes:
        """Of a lower-case word, a digit or a run of marks: what the splitter hands to the model."""
        out = self.cache.get(word)
        if out is None:
            known = word if word.isascii() else "".join(map(self.letters.__getitem__, word.encode()))
            out = self.cache[word] = self._bytes([t.id for t in self.tokenizer.model.tokenize(known)])
        return out

    def _new(self, piece: str) -> bytes:
        if PLAIN.fullmatch(piece):
            parts = PARTS.findall(piece.lower())
            out = self._word(parts[0]) if len(parts) == 1 else b"".join(map(self._word, parts))
        else:
            out = self._whole(piece)
        self.cache[piece] = out
        return out

    def encode(self, texts, end: int | None = None) -> list[np.ndarray]:
        """Ids of each text, then the end id if one is given."""
        import pyarrow as pa
        import pyarrow.compute as pc

        if not len(texts):
            return []
        if not self.by_piece:
            last = [] if end is None else [end]
            return [np.array(e.ids + last, self.kind) for e in self.tokenizer.encode_batch(list(texts), add_special_tokens=False)]
        pieces = pc.split_pattern(pc.replace_substring(pa.array(texts, pa.large_string()), "\n", " "), " ")
        coded = pieces.values.dictionary_encode()
        if len(self.cache) > self.limit:
            self.cache = {"": b""}
        get, new = self.cache.get, self._new
        encoded = [new(p) if (h := get(p)) is None else h for p in coded.dictionary.to_pylist()]
        flat = np.frombuffer(b"".join(encoded), self.kind)
        sizes = np.fromiter(map(len, encoded), np.int64, len(encoded)) // self.kind.itemsize
        starts = np.cumsum(sizes) - sizes
        codes = coded.indices.to_numpy()
        per = sizes[codes]
        ends = np.cumsum(per)
        ids = flat[np.repeat(starts[codes] - (ends - per), per) + np.arange(ends[-1] if len(ends) else 0)]
        bounds = np.concatenate(([0], ends))[pieces.offsets.to_numpy()]
        tail = np.array([] if end is None else [end], self.kind)
        return [np.concatenate((ids[a:b], tail)) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]


def encoder(path: str) -> PieceEncoder:
    state = worker_state("encoders")
    if path not in state:
        state[path] = PieceEncoder(path)
    return state[path]


def batches(values, budget: int = 12_000_000):
    """Bounds of slices of a list of texts with at most `budget` characters each, one text at least."""
    begin = size = 0
    for i, v in enumerate(values):
        if size and size + len(v) > budget:
            yield begin, i
            begin, size = i, 0
        size += len(v)
    if begin < len(values):
        yield begin, len(values)

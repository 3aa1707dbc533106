"""Vector bin packing of examples into sequences.

Every example asks for tokens, one segment and loss-bearing tokens; every sequence has a limit on each. The example goes
to the open sequence where the dot product of its demand and the sequence's room, both as shares of the limits, is
greatest among those that hold it whole. Where none does, it may be cut. Each task packs its own rows, in windows, and
carries its open sequences from window to window, so nothing is shuffled and at most one sequence per task stays short."""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, tidy, to_frame, whole
from .tokens import batches, encoder

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, loss_tokens long"


@dataclass
class Limits:
    tokens: int = 2048
    segments: int = 256
    loss: int = 2048
    open_bins: int = 24


@dataclass
class Bin:
    number: int
    tokens: int = 0
    segments: int = 0
    loss: int = 0
    pieces: list = field(default_factory=list)


class Packer:
    """Packs pieces (example, begin, end) and hands back full sequences. The first `head` tokens of an example bear no loss, all others do."""

    def __init__(self, limits: Limits):
        self.limits, self.open, self.next = limits, [], 0

    def _bin(self) -> Bin:
        self.open.append(Bin(self.next))
        self.next += 1
        return self.open[-1]

    @staticmethod
    def _loss(head: int, begin: int, end: int) -> int:
        return max(0, end - max(begin, head))

    def _fits(self, b: Bin, n: int, loss: int) -> bool:
        most = self.limits
        return b.tokens + n <= most.tokens and b.segments < most.segments and b.loss + loss <= most.loss

    def _longest(self, b: Bin, begin: int, end: int, head: int) -> int:
        """Tokens of [begin, end) that the bin still takes."""
        most = self.limits
        n = min(end - begin, most.tokens - b.tokens) if b.segments < most.segments else 0
        return min(n, max(0, head - begin) + most.loss - b.loss)

    def _put(self, b: Bin, example, begin: int, end: int, head: int) -> None:
        b.pieces.append((example, begin, end, b.tokens, self._loss(head, begin, end)))
        b.tokens += end - begin
        b.segments += 1
        b.loss += b.pieces[-1][-1]

    def _full(self, b: Bin) -> bool:
        most = self.limits
        return b.tokens >= most.tokens or b.segments >= most.segments

    def add(self, example, size: int, head: int = 0):
        """Place one example; yields the sequences that it fills."""
        most, begin = self.limits, 0
        while size - begin > 0:
            n = min(size - begin, most.tokens)
            loss = self._loss(head, begin, begin + n)
            if n == most.tokens and loss <= most.loss:
                b = Bin(self.next)
                self.next += 1
                self._put(b, example, begin, begin + n, head)
                yield b
                begin += n
                continue
            best, score = None, -1.0
            for b in self.open:
                if self._fits(b, n, loss):
                    s = n / most.tokens * (1 - b.tokens / most.tokens) + (1 - b.segments / most.segments) / most.segments + loss / most.loss * (1 - b.loss / most.loss)
                    if s > score:
                        best, score = b, s
            if best is None and len(self.open) < most.open_bins and loss <= most.loss:
                best = self._bin()
            if best is None:  # cut: the fullest sequence takes what it still can
                room = [(self._longest(b, begin, size, head), b) for b in self.open]
                room = [(k, b) for k, b in room if k > 0]
                if room:
                    n, best = min(room, key=lambda x: (x[0], x[1].number))
                else:
                    if self.open:
                        stuck = max(self.open, key=lambda b: (b.tokens, -b.number))
                        self.open.remove(stuck)
                        yield stuck
                    best = self._bin()
                    n = self._longest(best, begin, size, head)
                    if n <= 0:
                        raise ValueError("a limit is below one token")
            self._put(best, example, begin, begin + n, head)
            begin += n
            if self._full(best):
                self.open.remove(best)
                yield best

    def finish(self):
        """Close the open sequences: pieces of the emptiest move, cut where needed, into the gaps of the fullest."""
        left = sorted(self.open, key=lambda b: (-b.tokens, b.number))
        self.open = []
        while left:
            b = left.pop(0)
            while left and not self._full(b):
                donor = left[-1]
                example, begin, end, _, loss = donor.pieces.pop()
                head = example[2] if isinstance(example, tuple) and len(example) > 2 else 0
                n = self._longest(b, begin, end, head)
                donor.tokens -= end - begin
                donor.segments -= 1
                donor.loss -= loss
                if n > 0:
                    self._put(b, example, begin, begin + n, head)
                if begin + max(n, 0) < end:
                    self._put(donor, example, begin + max(n, 0), end, head)
                if not donor.pieces:
                    left.pop()
                if n <= 0:
                    break
            yield b


def pack_documents(docs: DataFrame, tokenizer_path: str, end_id: int = 1, limits: Limits | None = None, loss_from: str | None = None, prompt_share: float = 0.0) -> DataFrame:
    """One row per piece: (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, loss_tokens); every id of every document lies in exactly one piece.

    `loss_from` names a column with the first loss-bearing token of each example (an instruction's answer begins there);
    without it, the first `prompt_share` of an example's tokens is its prompt and bears no loss. Null text is an empty
    document of its end id only; null doc_id and repeated rows are packed like any other; documents that tie in length
    keep their order; an empty table gives no piece; other columns are ignored.
    """
    most = limits or Limits()
    head = F.lit(None).cast("long") if loss_from is None else F.greatest(F.coalesce(F.col(loss_from).cast("long"), F.lit(0)), F.lit(0))
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"), head.alias("head"))

    def pack(frames):
        from pyspark import TaskContext

        enc, packer, base = encoder(tokenizer_path), Packer(most), TaskContext.get().partitionId() << 32
        rows: list[tuple] = []

        def keep(sequences):
            for b in sequences:
                for (key, ids, _), begin, end, offset, loss in b.pieces:
                    rows.append((key, begin, end - begin, zlib.crc32(ids[begin:end].astype("<u4").tobytes()), len(ids), base + b.number, offset, loss))

        for frame in frames:
            texts, keys, heads = frame["text"].tolist(), whole(frame["doc_id"]), whole(frame["head"])
            for a, b in batches(texts):
                window = [(k, ids, int(prompt_share * len(ids)) if h is None else h) for k, ids, h in zip(keys[a:b], enc.encode(texts[a:b], end_id), heads[a:b], strict=True)]
                for example in sorted(window, key=lambda x: -(len(x[1]) % most.tokens)):
                    keep(packer.add(example, len(example[1]), example[2]))
                    if len(rows) >= 5000:
                        yield to_frame(rows, PIECES)
                        rows.clear()
        keep(packer.finish())
        if rows:
            yield to_frame(rows, PIECES)

    return chosen.mapInPandas(tidy(pack), PIECES)


ANSWERS = Limits(tokens=2048, segments=256, loss=1920)
PROMPT_SHARE = 0.25


def pack_answers(docs: DataFrame, tokenizer_path: str, end_id: int = 1, limits: Limits = ANSWERS) -> DataFrame:
    """Pack documents as instruction data: the first quarter of each is its prompt, and a sequence takes fewer loss-bearing tokens than tokens, so all three limits bind.

    The cases are those of pack_documents()."""
    return pack_documents(docs, tokenizer_path, end_id, limits, prompt_share=PROMPT_SHARE)

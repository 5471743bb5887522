"""Token counts under a SentencePiece BPE model by overlapping chunks that are spliced where both agree.

Proof of a stable boundary: a token that straddles the place between two
characters holds both, and so does each piece that it was merged from. Where no
piece of the vocabulary has the two side by side, every encoding of every text
has a boundary there, and what stands on one side has no effect on the other.
``stable`` asks the vocabulary, not a rule of thumb.

Every text is encoded in chunks of ``chunk`` characters with the offsets of their
tokens; neighbours overlap around their splice, a stable boundary that both
encodings must have, and each chunk counts the tokens between its splices. Where
an overlap holds no stable place it is widened, at last over whole chunks; where
the two encodings do not align at a splice, the two chunks become one. What is
held besides the text are chunks of one block of bounded size.

Defined cases: null text is empty, an empty text has no tokens, repeated rows
give repeated results, null doc_id is kept, very long texts are cut as all are,
extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The word mark of the model's pieces.
MARK = "▁"


class Chunk(NamedTuple):
    """Characters [start, stop) of a text, which counts the tokens that begin in [low, high)."""
    start: int
    low: int
    high: int
    stop: int


class PieceCounter:
    def __init__(self, path: str, chunk: int = 4096, overlap: int = 64):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_file=path)
        self.chunk, self.overlap = chunk, overlap
        pieces = [self.sp.id_to_piece(i) for i in range(self.sp.get_piece_size())]
        self.bigrams = {p[i:i + 2] for p in pieces for i in range(len(p) - 1)}
        #: bytes that a token stands for; a piece of a single byte is written as its number
        self.bytes_of = np.array([1 if self.sp.is_byte(i) else len(p.replace(MARK, " ").encode()) for i, p in enumerate(pieces)], np.int64)
        # an encoder that rewrites characters or drops spaces would need other offsets
        self.literal = all(self.sp.decode(self.sp.encode(t)) == t for t in ("a  b", " a", "a ", "ﬁ…①", "a\tb\nc"))

    def stable(self, text: str, x: int) -> bool:
        """Whether every encoding of ``text`` has a token boundary before character x."""
        return (text[x - 1] + text[x]).replace(" ", MARK) not in self.bigrams

    def splice(self, text: str, low: int, high: int) -> int | None:
        """The last stable place in (low, high]; looks through the overlap first, then wider."""
        wide = self.overlap
        while True:
            least = max(low, high - wide)
            for x in range(high, least, -1):
                if self.stable(text, x):
                    return x
            if least == low:
                return None
            high, wide = least, 2 * wide

    def chunks(self, text: str) -> list[Chunk]:
        """The chunks of a text; the mark that the model puts before each is none of its tokens' text."""
        n = len(text)
        # a text with the mark itself reads it as a space, which no offset would show
        if not self.literal or MARK in text:
            return [Chunk(0, 0, n, n)]
        places, want = [0], self.chunk
        while places[-1] + want < n:
            x = self.splice(text, places[-1], places[-1] + want)
            if x is None:
                want *= 2  # take in more text
            else:
                places.append(x)
                want = self.chunk
        places.append(n)
        return [Chunk(max(0, a - self.overlap), a, b, min(n, b + self.overlap)) for a, b in zip(places, places[1:])]

    def _encoded(self, text: str, c: Chunk, ids: list[int]) -> tuple[int, bool, bool]:
        """(tokens counted, whether the chunk has a boundary at its low and at its high splice)."""
        ends = np.cumsum(self.bytes_of[np.array(ids, np.int64)]) - 1 if ids else np.zeros(0, np.int64)  # the mark before the chunk is no byte of it
        a = len(text[c.start:c.low].encode("utf-8", "surrogatepass"))
        b = a + len(text[c.low:c.high].encode("utf-8", "surrogatepass"))
        before, upto = int(np.searchsorted(ends, a, side="right")), int(np.searchsorted(ends, b, side="right"))
        # tokens that end at or before the low splice are the neighbour's; at a text's start the mark may be a token alone
        return upto - (before if c.low else 0), not c.low or before > 0 and ends[before - 1] == a, c.high == len(text) or upto > 0 and ends[upto - 1] == b

    def _ids(self, texts: Iterator[str]) -> Iterator[list[int]]:
        for block in blocks(texts):
            yield from self.sp.encode(block, num_threads=1)

    def count_block(self, texts: list[str]) -> list[int]:
        cut = [self.chunks(t) if t else [] for t in texts]
        found = self._ids(t[c.start:c.stop] for t, own in zip(texts, cut) for c in own)
        out = []
        for text, own in zip(texts, cut):
            if len(own) == 1:
                out.append(len(next(found)))
                continue
            done = [(c, *self._encoded(text, c, next(found))) for c in own]
            out.append(self._spliced(text, done))
        return out

    def _spliced(self, text: str, done: list[tuple]) -> int:
        """The sum over aligned neighbours; two that are not aligned are encoded again as one chunk."""
        i = 0
        while i + 1 < len(done):
            (left, _, _, end), (right, _, begin, _) = done[i], done[i + 1]
            if end and begin:
                i += 1
                continue
            both = Chunk(left.start, left.low, right.high, right.stop)
            done[i:i + 2] = [(both, *self._encoded(text, both, self.sp.encode(text[both.start:both.stop], num_threads=1)))]
            i = max(0, i - 1)
        return sum(n for _, n, _, _ in done)

    def count(self, text: str) -> int:
        return self.count_block([text])[0]


@lru_cache(4)
def counter(path: str) -> PieceCounter:
    """One per Python worker."""
    return PieceCounter(path)


def blocks(texts: Iterable[str], size: int = 1 << 20) -> Iterator[list[str]]:
    """Runs of about ``size`` characters."""
    block, held = [], 0
    for t in texts:
        block.append(t)
        held += len(t)
        if held >= size:
            yield block
            block, held = [], 0
    if block:
        yield block


def token_counts(docs: DataFrame, path: str, limit: int = 4096) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit), a row for each row of ``docs``."""
    def run(batches):
        sp = counter(path)
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            n = [x for block in blocks(texts) for x in sp.count_block(block)]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(
        run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")

"""Byte-level BPE encoding as a bounded-lookahead streaming transducer, and incremental decoding.

A token sequence is the encoding of its bytes exactly if every token encodes to
itself and every two neighbours encode to themselves (the merge list is proper:
each merge joins what earlier ones made). So the encoding of a prefix has one
last token, found from the last tokens of shorter prefixes: the longest token
that ends there and goes with the last token before it. An automaton of all
tokens names those that end at each byte. A future token can only start at one of
the last ``lookahead`` positions, ``lookahead`` being the longest token of the
merge list in bytes. Tokens on which the chains of all those positions agree are
stable and go out; only what follows them is kept.

Every pre-token goes through the transducer. Those that a block of texts holds
for the first time pass it in one run, a start mark between them; what came out
is memoised in tables of bounded size. Long texts are cut into sections where no
pre-token can straddle, so the transducer, its memo and the decoder hold as much
for a long text as for a short one.

Defined cases: null text is empty; empty text gives no tokens; repeated rows
give repeated results; a null doc_id is kept; very long texts and pre-tokens are
streamed; extra columns are ignored. Special tokens inside a text are found
first, as the library does by default.
"""

from __future__ import annotations

import codecs
import hashlib
import json
import re
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import groupby

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The white space of the pre-tokenizer and its pattern.
SPACE = r"\t-\r \x85\xa0  -     　"
PATTERN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{SPACE}\p{{L}}\p{{N}}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+"
_INNER = re.compile(r"(?<=\S) (?=\S)")
_DOUBLE = re.compile(r"\s\s")
_NEVER = 1 << 60
#: stands between pre-tokens; no byte
_START = "\u0100"


def byte_alphabet() -> dict[str, int]:
    """Printable stand-ins of the 256 bytes: printable Latin-1 stays, the rest counts up from 256."""
    keep = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(keep)]
    return {chr(b): b for b in keep} | {chr(256 + n): b for n, b in enumerate(rest)}


class ByteBpe:
    def __init__(self, path: str, memo: int = 500_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet, vocab = byte_alphabet(), spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.bytes_of = [b""] * (max([*vocab.values(), *self.special.values()]) + 1)
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(map(alphabet.__getitem__, token)) if token not in self.special else token.encode()
        for token, i in self.special.items():
            self.bytes_of[i] = token.encode()
        self.first = [0] * 256
        for token, i in vocab.items():
            if len(token) == 1:
                self.first[alphabet[token]] = i
        # a pair of ids -> its rank; what the merge of that rank makes
        self.rank, self.made = {}, []
        for n, pair in enumerate(spec["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.rank[vocab[a] << 20 | vocab[b]] = n
            self.made.append(vocab[a + b])
        #: sufficient lookahead: no token is longer, so no future token starts before it
        self.lookahead = max(len(self.bytes_of[i]) for i in self.made)
        self._automaton = ahocorasick.Automaton()
        for i in {*self.first, *self.made}:
            self._automaton.add_word(self.bytes_of[i].decode("latin-1"), (i, len(self.bytes_of[i])))
        self._automaton.make_automaton()
        self._pairs: dict[int, bool] = {}
        self._pieces = regex.compile(PATTERN).findall
        self._split = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.memo, self._pretokens, self._chunks = memo, {}, {}

    def merge(self, data: bytes) -> list[int]:
        """All merges of a byte string, lowest rank and then leftmost first."""
        ids, rank, made = [self.first[b] for b in data], self.rank.get, self.made
        ranks = [rank(a << 20 | b, _NEVER) for a, b in zip(ids, ids[1:])]
        while ranks:
            best = min(ranks)
            if best == _NEVER:
                break
            i = ranks.index(best)
            ids[i:i + 2] = [made[best]]
            del ranks[i]
            if i:
                ranks[i - 1] = rank(ids[i - 1] << 20 | ids[i], _NEVER)
            if i < len(ranks):
                ranks[i] = rank(ids[i] << 20 | ids[i + 1], _NEVER)
        return ids

    def _goes(self, before: int, i: int) -> bool:
        """Whether token i encodes to itself, and behind token ``before`` (-1: none) both do; in a table of bounded size."""
        key = before << 20 | i
        ok = self._pairs.get(key)
        if ok is None:
            if len(self._pairs) > self.memo:
                self._pairs.clear()
            own = [i] if before < 0 else [before, i]
            ok = self._pairs[key] = (before < 0 or self._goes(-1, i)) and self.merge(b"".join(self.bytes_of[x] for x in own)) == own
        return ok

    def _advance(self, data: str, last: list[int], sizes: list[int]) -> None:
        """Append, for the positions of ``data`` from ``len(last) - 1`` on, the last token of the encoding up to there
        and its length; -1 and 0 where a pre-token starts."""
        begin = len(last) - 1
        back = max(0, begin - self.lookahead)
        part = data[back:]
        more = len(data) - begin
        last += [-1] * more
        sizes += [0] * more
        done, goes, known, ahead = begin, self._goes, self._pairs.get, back + 1
        for end, (i, n) in self._automaton.iter(part):
            end += ahead
            if end <= done:  # the longest that fits comes first
                continue
            start = end - n
            if start < 0:
                continue
            before = last[start]
            ok = known(before << 20 | i)
            if ok or ok is None and goes(before, i):
                last[end], sizes[end], done = i, n, end

    def transduce(self, words: Iterable[bytes], step: int = 1 << 16) -> Iterator[list[int]]:
        """Tokens of each pre-token; they pass the transducer in runs of about ``step`` bytes, longer ones alone."""
        run: list[bytes] = []
        held = 0
        for w in words:
            if len(w) >= step:
                yield from self._passed(run)
                run, held = [], 0
                yield [i for part in self.stream([w]) for i in part]
                continue
            run.append(w)
            held += len(w)
            if held >= step:
                yield from self._passed(run)
                run, held = [], 0
        yield from self._passed(run)

    def _passed(self, run: list[bytes]) -> Iterator[list[int]]:
        data = _START.join(w.decode("latin-1") for w in run)
        last, sizes = [-1], [0]
        self._advance(data, last, sizes)
        at = 0
        for w in run:
            at += len(w)
            out, p, start = [], at, at - len(w)
            while p > start:
                out.append(last[p])
                p -= sizes[p]
            yield out[::-1]
            at += 1

    def stream(self, pieces: Iterable[bytes], step: int = 1024) -> Iterator[list[int]]:
        """Tokens of one pre-token that arrives in pieces, as soon as they are stable."""
        data, last, sizes = "", [-1], [0]  # last[0]: the last token that went out
        for piece in pieces:
            for at in range(0, len(piece), step):
                data += piece[at:at + step].decode("latin-1")
                self._advance(data, last, sizes)
                stable = self._agreed(last, sizes)
                if stable:
                    out = self._chain(last, sizes, stable)
                    data, last, sizes = data[stable:], [out[-1], *last[stable + 1:]], [0, *sizes[stable + 1:]]
                    yield out
        yield self._chain(last, sizes, len(last) - 1)

    def _agreed(self, last: list[int], sizes: list[int]) -> int:
        """The largest position on which the chains of all live positions agree; 0: none."""
        live = set(range(max(0, len(last) - self.lookahead), len(last)))
        while len(live) > 1:
            p = max(live)
            live.remove(p)
            if p == 0:
                return 0
            live.add(p - sizes[p])
        return live.pop()

    def _chain(self, last: list[int], sizes: list[int], p: int) -> list[int]:
        out = []
        while p:
            out.append(last[p])
            p -= sizes[p]
        return out[::-1]

    def _learn(self, texts: list[list[str]]) -> None:
        """Make sure that all chunks of a block of texts are in the memo."""
        if len(self._chunks) > self.memo:
            self._chunks.clear()
        if len(self._pretokens) > self.memo:
            self._pretokens.clear()
        new = set().union(*texts).difference(self._chunks)
        parts = {c: self._pretokens_of(c) for c in new}
        fresh = list(set().union(*parts.values()).difference(self._pretokens))
        coded = self.transduce(p.encode("utf-8", "surrogatepass") for p in fresh)
        self._pretokens.update((p, np.array(ids, "<u4").tobytes()) for p, ids in zip(fresh, coded))
        get = self._pretokens.__getitem__
        self._chunks.update({c: get(c) if v[0] is c else b"".join(map(get, v)) for c, v in parts.items()})

    def _pretokens_of(self, chunk: str) -> list[str]:
        """The pattern's matches; words of letters alone, or with one ASCII mark behind, need no search."""
        body = chunk[1:] if chunk[0] == " " else chunk
        if body.isalpha():
            return [chunk]
        if body and body[-1] in ".,;:!?" and body[:-1].isalpha():
            return [chunk[:-1], chunk[-1]]
        return self._pieces(chunk)

    def _cut(self, text: str) -> list[str]:
        """Chunks that no pre-token straddles: one always starts at a single space between two that are none."""
        if not text:
            return []
        if text[0].isspace() or text[-1].isspace() or _DOUBLE.search(text):
            first, *rest = _INNER.split(text)
        else:
            first, *rest = text.split(" ")
        return [first, *[" " + c for c in rest]]

    def encode_block(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        parts = [[t] if not any(s in t for s in self.special) else [p for p in self._split.split(t) if p] for t in texts]
        cut = [[[p] if p in self.special else self._cut(p) for p in t] for t in parts]
        self._learn([c for t, own in zip(parts, cut) for p, c in zip(t, own) if p not in self.special])
        get = self._chunks.__getitem__
        return [b"".join(np.uint32(self.special[p]).astype("<u4").tobytes() if p in self.special else b"".join(map(get, c)) for p, c in zip(t, own)) for t, own in zip(parts, cut)]

    def sections(self, text: str, size: int = 1 << 18) -> Iterator[str]:
        """Parts of about ``size`` characters that no pre-token straddles: each starts at a space between two that are none."""
        at = 0
        while len(text) - at > size:
            cut = _INNER.search(text, at + size)
            if cut is None:
                break
            yield text[at:cut.start()]
            at = cut.start()
        yield text[at:] if at else text

    def encode_many(self, texts: Iterable[str | None], size: int = 1 << 18) -> Iterator[tuple[int, bytes]]:
        """(number of the text, ids of its next section), block by block of about ``size`` characters; null as empty."""
        block, held = [], 0
        for i, t in enumerate(texts):
            for part in self.sections(t or "", size):
                block.append((i, part))
                held += len(part)
                if held >= size:
                    yield from zip([i for i, _ in block], self.encode_block([p for _, p in block]))
                    block, held = [], 0
        yield from zip([i for i, _ in block], self.encode_block([p for _, p in block]))

    def encode_sections(self, text: str) -> Iterator[bytes]:
        return (ids for _, ids in self.encode_many([text]))

    def encode(self, text: str) -> bytes:
        return b"".join(self.encode_sections(text))

    def decoder(self):
        """Feeds on ids and gives the text that they make certain: an incremental UTF-8 state machine over the bytes of the tokens."""
        state, look = codecs.getincrementaldecoder("utf-8")("replace"), self.bytes_of.__getitem__
        return lambda ids, final=False: state.decode(b"".join(map(look, np.frombuffer(ids, "<u4").tolist())), final)

    def decode(self, ids: bytes, step: int = 1 << 16) -> Iterator[str]:
        feed = self.decoder()
        for at in range(0, len(ids), 4 * step):
            yield feed(ids[at:at + 4 * step])
        yield feed(b"", True)


@lru_cache(4)
def tokenizer(path: str) -> ByteBpe:
    """One per Python worker."""
    return ByteBpe(path)


_KINDS = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}


def _rows(frame: DataFrame, keep: list[str], source: str, path: str, fields: str, made) -> DataFrame:
    """``keep`` columns, those of a result's name left out, with ``fields``, made from the ``source`` column of a
    batch by ``made(bpe, values)``."""
    names, kinds = zip(*(f.split() for f in fields.split(", ")))
    keep = [c for c in dict.fromkeys(keep) if c not in names]

    def run(batches):
        bpe = tokenizer(path)
        for b in batches:
            rows = made(bpe, b.column(b.num_columns - 1).to_pylist())
            cols = list(zip(*rows)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *(pa.array(c, _KINDS[k]) for c, k in zip(cols, kinds))], names=[*keep, *names])

    kept = [F.col(c) for c in keep]
    schema = ", ".join([*(f"`{c}` {frame.schema[c].dataType.simpleString()}" for c in keep), fields])
    return frame.select(*kept, source).mapInArrow(run, schema)


def _by_text(bpe: ByteBpe, texts: list[str | None]) -> Iterator[Iterator[bytes]]:
    """The sections' ids of each text in turn."""
    for _, parts in groupby(bpe.encode_many(texts), key=lambda x: x[0]):
        yield (ids for _, ids in parts)


def encode(docs: DataFrame, path: str, keep: list[str] | None = None) -> DataFrame:
    """The ``keep`` columns with n_tokens and ids (little-endian unsigned 32-bit)."""
    def made(bpe, texts):
        return [(len(x) // 4, x) for x in (b"".join(parts) for parts in _by_text(bpe, texts))]

    return _rows(docs, keep or ["doc_id"], "text", path, "n_tokens long, ids binary", made)


def decode(encoded: DataFrame, path: str, keep: list[str] | None = None) -> DataFrame:
    """The ``keep`` columns with the text decoded from ``ids``."""
    return _rows(encoded, keep or ["doc_id"], "ids", path, "text string", lambda bpe, ids: [("".join(bpe.decode(x or b"")),) for x in ids])


def round_trip(docs: DataFrame, path: str, keep: list[str] | None = None, with_ids: bool = False) -> DataFrame:
    """The ``keep`` columns with n_tokens and the digests of the ids and of the text decoded from them,
    and with ``with_ids`` the ids."""
    def digests(bpe, parts):
        n, coded, text, feed, held = 0, hashlib.sha256(), hashlib.sha256(), bpe.decoder(), []
        for ids in parts:
            n += len(ids) // 4
            coded.update(ids)
            text.update(feed(ids).encode())
            if with_ids:
                held.append(ids)
        text.update(feed(b"", True).encode())
        return (n, coded.hexdigest(), text.hexdigest(), b"".join(held))[:width]

    def made(bpe, texts):
        return [digests(bpe, parts) for parts in _by_text(bpe, texts)]

    fields = "n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * with_ids
    width = 3 + with_ids
    return _rows(docs, keep or ["doc_id"], "text", path, fields, made)

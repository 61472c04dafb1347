"""Byte-level BPE encoding and decoding by prefix dynamic programming.

For every prefix of a byte string there is exactly one token with which its encoding can end. The table of
these last tokens is built from left to right: a token that ends at j is the last one iff it is compatible
with the last token of the prefix before it, that is, iff the two side by side encode to just these two.
Reading the table backwards gives the encoding; appending bytes only adds entries, and an edit redoes entries
only from the edit to where the old ones hold again.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import trimmed

#: Unicode's White_Space, the meaning of \s in the tokenizers' patterns, as the inside of a character class.
SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
#: Words that a task remembers, their characters, and pairs of tokens, before it starts anew; characters of texts that it
#: encodes together. They bound memory and change no result.
MEMORY, LETTERS, PAIRS, TOGETHER = 250_000, 1 << 24, 400_000, 1 << 23
FOREVER = float("inf")


def read_ranks(path: str) -> dict[bytes, int]:
    """The ranks of a vocabulary file with one base64 token and its rank a line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Codec:
    """Encodes and decodes with one vocabulary; each match of the pattern is encoded separately."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        import regex

        self.ranks, self.tokens = ranks, {v: k for k, v in ranks.items()}
        spelled = pattern.replace(r"[^\s", f"[^{SPACE}").replace(r"\S", f"[^{SPACE}]").replace(r"\s", f"[{SPACE}]")
        self.pieces = regex.compile(spelled).findall
        #: Where a space inside a run of white space forbids to cut before it.
        self.knot = re.compile(f"[{SPACE}] [{SPACE}]").search
        self.longest = max(map(len, ranks), default=1)
        self.left: dict[int, list] = {}
        self.right: dict[int, list] = {}
        self.fits: dict[int, bool] = {}
        self.own: dict[int, bool] = {}
        #: Ids of words, each with a space before it, and of single pieces.
        self.spaced: dict[str, tuple[int, ...]] = {}
        self.single: dict[str, tuple[int, ...]] = {}
        self.letters = 0
        #: Tokens spelled backwards as a tree: (node * 256 + byte) -> node, and the token that ends at a node.
        self.back: dict[int, int] = {}
        self.ends = [-1]
        for t, i in ranks.items():
            node = 0
            for byte in reversed(t):
                node = self.back.setdefault(node << 8 | byte, len(self.ends))
                if node == len(self.ends):
                    self.ends.append(-1)
            self.ends[node] = i

    def by_merging(self, data: bytes, below: float = FOREVER) -> list[bytes]:
        """The plain way: merge the leftmost adjacent pair of lowest rank, while one has a rank below the limit."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > 1:
            rank, i = min((self.ranks.get(parts[i] + parts[i + 1], FOREVER), i) for i in range(len(parts) - 1))
            if rank >= below:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def history(self, token: int, side: int) -> list[tuple[bytes, float]]:
        """What stands at the token's left (0) or right (-1) end while it forms: (bytes, rank that replaces them)."""
        known = (self.right if side else self.left).setdefault(token, [])
        if not known:
            end, data, spans = FOREVER, self.tokens[token], []
            while True:
                spans.append((data, end))
                if len(data) == 1:
                    break
                end = self.ranks[data]
                data = self.by_merging(data, below=end)[side]
            known.extend(reversed(spans))
        return known

    def compatible(self, a: int, b: int) -> bool:
        """Whether the bytes of a and b together encode to exactly a, b.

        Follows both sides of the border through time; no pair across it may merge before one of the two
        grows on its own. Of merges with equal rank the left one comes first.
        """
        good = self.fits.get(a << 24 | b)
        if good is None:
            lefts, rights, i, j, good = self.history(a, -1), self.history(b, 0), 0, 0, True
            while True:
                (x, x_end), (y, y_end) = lefts[i], rights[j]
                rank = self.ranks.get(x + y, FOREVER)
                if rank < x_end and rank <= y_end and rank < FOREVER:
                    good = False
                    break
                if x_end == y_end == FOREVER:
                    break
                if x_end <= y_end:
                    i += 1
                else:
                    j += 1
            if len(self.fits) >= PAIRS:
                self.fits.clear()
            self.fits[a << 24 | b] = good
        return good

    def stands(self, token: int) -> bool:
        """Whether merging the token's bytes ends at the token; one that doesn't is only used as a whole piece."""
        if token not in self.own:
            self.own[token] = len(self.by_merging(self.tokens[token])) == 1
        return self.own[token]

    def extend(self, data: bytes, last: list[int], start: int) -> None:
        """Adds the last tokens of the prefixes that end behind each byte from start on."""
        step, ends, fits = self.back.get, self.ends, self.fits
        for end in range(start, len(data)):
            at, node, found = end, step(data[end]), []
            while node is not None:
                at -= 1
                if ends[node] >= 0:
                    found.append((at, ends[node]))
                if at < 0:
                    break
                node = step(node << 8 | data[at])
            for before, token in reversed(found):
                if before < 0:
                    good = self.stands(token)
                else:
                    good = fits.get(last[before] << 24 | token)
                    if good is None:
                        good = self.stands(token) and self.compatible(last[before], token)
                if good:
                    last.append(token)
                    break

    def walk(self, last: list[int]) -> list[int]:
        """The encoding that a table of last tokens stands for."""
        ids, at = [], len(last)
        while at:
            ids.append(last[at - 1])
            at -= len(self.tokens[ids[-1]])
        return ids[::-1]

    def learn(self, pieces: set[str]) -> None:
        """Encodes pieces in sorted order: each table goes on from the prefix it shares with the one before."""
        last, before = [], b""
        for piece, data in sorted((p, p.encode()) for p in pieces if p not in self.single):
            self.letters += len(data)
            whole = self.ranks.get(data)
            if whole is not None:
                self.single[piece] = (whole,)
                continue
            same, most = 0, min(len(data), len(before))
            while same < most and data[same] == before[same]:
                same += 1
            del last[same:]
            self.extend(data, last, same)
            self.single[piece] = tuple(self.walk(last))
            before = data

    def prepare(self, texts: list[str]) -> None:
        """Makes all words of the texts known, the new ones together; forgets all first when there are many."""
        if len(self.spaced) + len(self.single) >= 2 * MEMORY or self.letters >= LETTERS:
            self.spaced.clear()
            self.single.clear()
            self.letters = 0
        new: set[str] = set()
        for text in texts:
            new.update(text.split(" "))
        split = {w: (" " + w,) if w.isalpha() else self.pieces(" " + w) for w in new if w not in self.spaced}
        self.learn(set(chain.from_iterable(split.values())))
        single = self.single
        for w, pieces in split.items():
            self.spaced[w] = single[pieces[0]] if len(pieces) == 1 else tuple(chain.from_iterable([single[p] for p in pieces]))

    def encode_all(self, texts: Iterable[str]) -> Iterator[list[int]]:
        """The ids of whole texts, of any length; an empty text has none.

        A match of the pattern never goes on over a space that follows something else than white space, so
        words with the space before them are encoded as a whole, and each different word once.
        """
        some, letters = [], 0
        for text in texts:
            if some and letters + len(text) > TOGETHER:
                yield from self.encode_some(some)
                some, letters = [], 0
            some.append(text)
            letters += len(text)
        yield from self.encode_some(some)

    def encode_some(self, texts: list[str]) -> Iterator[list[int]]:
        knots = [bool(self.knot(x)) for x in texts]
        self.prepare([x for x, knot in zip(texts, knots) if not knot])
        spaced = self.spaced
        for text, knot in zip(texts, knots):
            if knot:
                pieces = self.pieces(text)
                self.learn(set(pieces))
                yield list(chain.from_iterable([self.single[p] for p in pieces]))
            else:
                first, *more = text.split(" ")
                pieces = self.pieces(first)
                self.learn(set(pieces))
                yield list(chain(chain.from_iterable([self.single[p] for p in pieces]), chain.from_iterable([spaced[w] for w in more])))

    def encode(self, text: str) -> list[int]:
        return next(self.encode_all([text]))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join([self.tokens[i] for i in ids])


class PrefixTable:
    """The last token of every prefix of one piece, kept up to date through appends and edits."""

    def __init__(self, codec: Codec, data: bytes = b"") -> None:
        self.codec, self.data, self.last = codec, b"", []
        self.append(data)

    def append(self, more: bytes) -> None:
        """Lengthens the piece; what the table holds stays as it is."""
        start, self.data = len(self.data), self.data + more
        self.codec.extend(self.data, self.last, start)

    def edit(self, start: int, stop: int, put: bytes) -> int:
        """Replaces data[start:stop] by put and returns how many entries were computed.

        An entry depends on its bytes and on entries at most one token's length back: behind the edit, once
        as many in a row come out as before, all later ones hold too.
        """
        old, tail = self.last, len(self.data) - stop
        self.data = self.data[:start] + put + self.data[stop:]
        last, done, same, step = old[:start], start, 0, self.codec.longest
        while done < len(self.data):
            self.codec.extend(self.data[: done + step], last, done)
            for at in range(done, len(last)):
                behind = at + 1 - (len(self.data) - tail)
                same = same + 1 if behind > 0 and last[at] == old[stop + behind - 1] else 0
            done = len(last)
            if same >= step:
                last += old[stop + done - (len(self.data) - tail) :]
                break
        self.last = last
        return done - start

    def ids(self) -> list[int]:
        return self.codec.walk(self.last)


def encoded(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", digests: bool = False) -> DataFrame:
    """Ids and decoded bytes of every text: id_col, n_tokens, ids array<int>, decoded binary.

    With digests, ids_sha256 and decoded_sha256 (of the decimal ids joined by one space, and of the decoded
    bytes) take the place of the two long columns. A null text counts as empty: no ids, no bytes. Texts of any length are
    encoded whole. Rows that repeat are encoded each, and a null id stays null; other columns are not read; an empty table
    gives an empty result. path is read on the driver.
    """
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(path))  # one vocabulary: a fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(ranks.value, pattern)
        names = {i: str(i) for i in codec.tokens}
        for batch in batches:
            keys, texts = batch.column(0), (x or "" for i in range(0, batch.num_rows, 64) for x in batch.column(1).slice(i, 64).to_pylist())
            counts, first, second = [], [], []
            for ids in codec.encode_all(texts):
                data = codec.decode(ids)
                counts.append(len(ids))
                if digests:
                    first.append(hashlib.sha256(" ".join([names[i] for i in ids]).encode()).hexdigest())
                    second.append(hashlib.sha256(data).hexdigest())
                else:
                    first.append(ids)
                    second.append(data)
            kinds = (pa.string(), pa.string()) if digests else (pa.list_(pa.int32()), pa.binary())
            yield pa.RecordBatch.from_arrays([keys, pa.array(counts, pa.int64()), pa.array(first, kinds[0]), pa.array(second, kinds[1])], names=out_names)

    out_names = [id_col, "n_tokens", *(("ids_sha256", "decoded_sha256") if digests else ("ids", "decoded"))]
    kinds = ("string", "string") if digests else ("array<int>", "binary")
    d = docs.select(F.col(id_col), F.col(text_col).cast("string"))
    schema = f"`{id_col}` {d.schema[0].dataType.simpleString()}, n_tokens bigint, {out_names[2]} {kinds[0]}, {out_names[3]} {kinds[1]}"
    return d.mapInArrow(trimmed(run), schema)

"""Exact token counts of every prefix by dynamic programming.

Byte-pair merging has one property that makes counts cheap: the encoding of a
string, cut before its last token, is the encoding of the rest. So a table
over the prefixes of a piece suffices, with the last token of each: a token t
that ends at i continues the prefix that ends at its start j exactly if the
two tokens s (last at j) and t encode as themselves side by side. One walk
gives the count of every prefix, from which totals, truncation points and
budget questions are read without encoding again.

A text is first cut into pieces by the vocabulary's published pattern, and
pieces are counted once per task; a text's table is a running sum over them.
Prefixes that end inside a piece take that piece's table, with the two cases
in which the pattern cuts a truncated text otherwise (white space before a
word, contractions) put right.

Defined results: null and empty texts count 0. The special string of the
vocabulary counts 1, as the library does by default.
"""

from __future__ import annotations

import json
import re
import unicodedata
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from gradsift.llm.textkit import Measure, annotate, per_process, slices

#: Fixed values of the public byte-level vocabulary.
SPECIAL = "<|endoftext|>"
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
SPACE = "\\t-\\r \\x85\\xa0"
#: Texts below this code point are cut with plain ranges, others by the library's own cutter.
NARROW = 0x250

#: Pieces whose counts are kept in a Python worker before it starts anew.
MOST_PIECES = 800_000


def _ranges(kind: str) -> str:
    found = [c for c in range(NARROW) if unicodedata.category(chr(c))[0] == kind]
    edges = [c for c in found if c - 1 not in found], [c for c in found if c + 1 not in found]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in zip(*edges, strict=True))


def _pattern(letters: str, numbers: str, space: str) -> str:
    return "|".join([*CONTRACTIONS, f" ?[{letters}]+", f" ?[{numbers}]+", f" ?[^{space}{letters}{numbers}]+", f"[{space}]+(?![^{space}])", f"[{space}]+"])


def byte_symbols() -> dict[str, int]:
    """The printable character that the vocabulary file writes for each byte:
    visible Latin-1 bytes stand for themselves, the rest follow from U+0100."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(0x100 + i): b for i, b in enumerate(hidden)}


class PrefixCounter:
    """Counts of one byte-level vocabulary (a tokenizers .json file)."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        symbol = byte_symbols()
        as_bytes = lambda s: bytes(symbol[c] for c in s)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        self.rank = {(as_bytes(a), as_bytes(b)): i for i, (a, b) in enumerate(pairs)}
        self.made = {a + b: (a, b) for a, b in self.rank}
        self.born = {a + b: i for (a, b), i in self.rank.items()}
        self.tokens = {bytes([b]) for b in range(256)} | self.made.keys()
        self.beside: dict[tuple[bytes, bytes], bool] = {}
        self.totals = _Totals(self)
        self.narrow = re.compile(_pattern(_ranges("L"), _ranges("N"), SPACE))
        self.cutter = Tokenizer.from_file(path).pre_tokenizer

    def pieces(self, text: str) -> list[str]:
        if text.isascii() or max(text) < chr(NARROW):
            return self.narrow.findall(text)
        return [text[a:b] for _, (a, b) in self.cutter.pre_tokenize_str(text)]

    def joins(self, s: bytes, t: bytes) -> bool:
        """Whether s and t, side by side, encode as themselves.

        Undo their merges from the latest on; at every moment only the two
        tokens at the seam could have merged, and did so if that merge comes
        before the one just undone. Of equal merges the left one is first.
        """
        key, bound = (s, t), 1 << 60
        answer = True
        while True:
            seam = self.rank.get((s, t))
            if seam is not None and seam < bound:
                answer = False
                break
            left, right = self.born.get(s, -1), self.born.get(t, -1)
            if left < 0 and right < 0:
                break
            if left > right:
                bound, s = left, self.made[s][1]
            else:
                bound, t = right + 1, self.made[t][0]
        if len(self.beside) > 500_000:
            self.beside.clear()
        self.beside[key] = answer
        return answer

    def table(self, piece: bytes, last: list[bytes] | None = None, count: list[int] | None = None) -> list[int]:
        """Token counts of the byte prefixes 0..len of one piece. last and
        count: the tables of a prefix of it, which are continued."""
        tokens, known, joins = self.tokens, self.beside.get, self.joins
        last, count = ([b""], [0]) if last is None else (last, count)
        for i in range(len(last), len(piece) + 1):
            j = i
            while j:
                j -= 1
                t = piece[j:i]
                if t in tokens:
                    if not j:
                        break
                    ok = known((last[j], t))
                    if ok or ok is None and joins(last[j], t):
                        break
            last.append(t)
            count.append(count[j] + 1)
        return count

    def learn(self, pieces: set[str]) -> None:
        """Total counts of new pieces, in order, each continuing the table of
        the prefix that it shares with the one before."""
        fresh = sorted(p.encode() for p in pieces if p not in self.totals)
        if len(self.totals) + len(fresh) > MOST_PIECES:
            self.totals.clear()
            fresh = sorted(p.encode() for p in pieces)
        before, last, count = b"", [b""], [0]
        for piece in fresh:
            n = _shared(before, piece)
            del last[n + 1 :], count[n + 1 :]
            self.totals[piece.decode()] = self.table(piece, last, count)[-1]
            before = piece

    def total(self, text: str) -> int:
        """Tokens of a whole text: the last entry of its prefix table."""
        if SPECIAL in text:
            parts = text.split(SPECIAL)
            return sum(map(self.total, parts)) + len(parts) - 1
        return sum(map(self.totals.__getitem__, self.pieces(text)))

    def prefixes(self, text: str) -> list[int]:
        """Token counts of the code-point prefixes 0..len of a text."""
        out, done, parts = [0], 0, text.split(SPECIAL)
        for n, part in enumerate(parts):
            ends = n < len(parts) - 1
            got = self._plain(part + SPECIAL[:-1] if ends else part)
            out += [done + c for c in got[1:]]
            done += got[len(part)]
            if ends:
                done += 1
                out.append(done)
        return out

    def _plain(self, text: str) -> list[int]:
        out, done, before = [0], 0, ""
        for piece in self.pieces(text):
            table = self.table(piece.encode())
            marks = list(accumulate(len(c.encode()) for c in piece))
            got = [done + table[m] for m in marks]
            if piece in CONTRACTIONS and len(piece) > 2:
                got[1] = done + self.total(piece[0]) + self.total(piece[1])
            if before and before.isspace() and piece[0].isspace():
                got[0] = done - self.totals[before] + self.totals[before + piece[0]]
            out += got
            done += table[-1]
            before = piece
        return out

    def longest_within(self, text: str, limit: int) -> int:
        """Code points of the longest prefix of at most limit tokens."""
        if len(text) <= limit // 4:  # no code point has more than four bytes, and no byte more than a token
            return len(text)
        if SPECIAL in text:
            return max(i for i, c in enumerate(self.prefixes(text)) if c <= limit)
        pieces = self.pieces(text)
        sums = list(accumulate(map(self.totals.__getitem__, pieces)))
        if not sums or sums[-1] <= limit:
            return len(text)
        full = next(i for i, c in enumerate(sums) if c > limit)
        # the table is exact from any piece on; one piece earlier for white space before a word, two later for what a cut changes
        first = max(0, full - 1)
        base, at = (sums[first - 1] if first else 0), sum(map(len, pieces[:first]))
        local = self.prefixes("".join(pieces[first : full + 3]))
        return at + max(i for i, c in enumerate(local) if base + c <= limit)


def _shared(a: bytes, b: bytes) -> int:
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


class _Totals(dict):
    """Token count by piece, found on first use."""

    def __init__(self, counter: PrefixCounter):
        self.counter = counter

    def __missing__(self, piece: str) -> int:
        if len(self) > MOST_PIECES:
            self.clear()
        got = self[piece] = self.counter.table(piece.encode())[-1]
        return got


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


COUNTS = T.StructType([T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType()), T.StructField("chars_within_limit", T.LongType())])


def token_counts(docs: DataFrame, text: str = "text", vocab: str = "byte_bpe_50k.json", limit: int = 512, keep: list[str] | None = None) -> DataFrame:
    """Add bytes, exact tokens, whether they exceed limit, and the code
    points of the longest prefix within limit, to each row of docs."""

    def start() -> Measure:
        counter = per_process(f"prefix:{vocab}", lambda: PrefixCounter(vocabulary(vocab)))

        def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
            texts = [t.decode() for t in slices(data, offsets)]
            counter.learn({p for t in texts for p in counter.pieces(t)})
            tokens = [counter.total(t) for t in texts]
            within = [len(t) if n <= limit else counter.longest_within(t, limit) for t, n in zip(texts, tokens, strict=True)]
            return {"n_bytes": np.diff(offsets), "n_tokens": tokens, "over_limit": [n > limit for n in tokens], "chars_within_limit": within}

        return measure

    return annotate(docs, text, COUNTS, start, keep, limit=8 << 20)


def prefix_table(docs: DataFrame, text: str = "text", vocab: str = "byte_bpe_50k.json", keep: list[str] | None = None) -> DataFrame:
    """Add prefix_tokens, the token count of every code-point prefix."""

    def start() -> Measure:
        counter = PrefixCounter(vocabulary(vocab))
        return lambda part, data, offsets: {"prefix_tokens": [counter.prefixes(t.decode()) for t in slices(data, offsets)]}

    return annotate(docs, text, T.StructType([T.StructField("prefix_tokens", T.ArrayType(T.IntegerType()))]), start, keep)

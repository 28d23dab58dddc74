"""Quality rules from tokeniser fertility.

A public vocabulary with byte fallback is a yardstick for text: prose in a
language that it knows takes few tokens for its characters, rarely falls back
to bytes, and spreads over many tokens. Per text we measure

    chars_per_token  code points in words per token,
    byte_share       share of tokens that are fallback bytes,
    token_entropy    entropy of the token distribution, in bits,

and hold them against the bands of the text's language or, where that has
none, of its main script. Every word is encoded once per worker and looked up
afterwards; the counts of a text are sums over its words.

The base rules need the same words: too few of them, or too many inside
three-word windows that the text repeats.

Defined results: null and wordless texts have zero counts and fail the base;
unknown languages use the bands of the script, unknown scripts the widest.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from gradsift.llm.textkit import BLANK_WORDS, CHUNK_BYTES, Words, annotate, byte_ranges, covered, mix, per_doc, per_process, select_rows, words_of

VOCABULARY = "piece_bpe_32k.model"
MOST_WORDS = 250_000


@dataclass(frozen=True)
class Band:
    """Accepted range of each measure; entropy as a share of what so many
    tokens allow, because short texts cannot reach the entropy of long ones."""

    least_chars: float
    most_chars: float
    most_bytes: float
    least_spread: float


#: Rejection bands. Latin-script prose takes 1.7 to 6 characters a token in
#: such a vocabulary; scripts with large alphabets about one, and they fall
#: back to bytes for rare characters. All-capital or symbol-laden text falls
#: under the first bound, long runs of one character over the second, and
#: text of few different tokens under the last. The first and last bound of a
#: language are the 0.5 % quantiles, rounded down, over the sample tables'
#: documents (0.1) labelled quality 1 and toxic 0 that pass the base rules:
#: 1,739 en, 421 de, 428 fr, 284 es. No such sample covers other languages, so
#: the bands of scripts are wide.
LANGUAGES = {
    "en": Band(2.066, 6.5, 0.05, 0.621),
    "de": Band(2.071, 6.5, 0.05, 0.601),
    "fr": Band(1.753, 6.5, 0.05, 0.596),
    "es": Band(1.802, 6.5, 0.05, 0.605),
}
SCRIPTS = {
    "latin": Band(1.5, 8.0, 0.15, 0.5),
    "cyrillic": Band(1.2, 8.0, 0.3, 0.5),
    "greek": Band(0.8, 6.0, 0.5, 0.5),
    "cjk": Band(0.3, 3.0, 0.9, 0.4),
    "other": Band(0.2, 20.0, 1.0, 0.3),
}
#: First and last code point of the blocks that tell a script.
BLOCKS = {"latin": [(0x41, 0x5A), (0x61, 0x7A), (0xC0, 0x24F)], "cyrillic": [(0x400, 0x52F)], "greek": [(0x370, 0x3FF)], "cjk": [(0x3040, 0x30FF), (0x3400, 0x9FFF), (0xAC00, 0xD7AF)]}

LEAST_WORDS = 50
MOST_REPEATED = 50
SYMBOLS = b"#*$%&|<>"

RULES = T.StructType(
    [T.StructField(n, T.LongType()) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    + [T.StructField(n, T.BooleanType()) for n in ("base_failed", "kept")]
    + [T.StructField("n_tokens", T.LongType())]
    + [T.StructField(n, T.DoubleType()) for n in ("chars_per_token", "byte_share", "token_entropy")]
    + [T.StructField("script", T.StringType())]
)


def base_counts(w: Words, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """The counts of the base rules of every text of a chunk."""
    data, n = w.data, len(w.counts)
    heads = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    symbol = np.zeros(256, bool)
    symbol[list(SYMBOLS)] = True
    marks = np.concatenate([[0], np.cumsum(symbol[data])])
    out = {"n_words": w.counts, "word_chars": per_doc(heads[w.ends] - heads[w.starts], w.doc, n), "n_symbols": marks[offsets[1:]] - marks[offsets[:-1]]}

    breaks = np.flatnonzero(data == 0x0A)
    starts = np.unique(np.concatenate([offsets[:-1], breaks + 1]))
    starts = starts[starts < len(data)]
    ends = np.minimum(np.concatenate([starts[1:], [len(data)]]), len(data)) if len(starts) else starts
    of = np.searchsorted(offsets, starts, "right") - 1
    ends = np.where((ends > starts) & (data[ends - 1] == 0x0A), ends - 1, ends)
    has_word = np.searchsorted(w.starts, ends) > np.searchsorted(w.starts, starts)
    starts, ends, of = starts[has_word], ends[has_word], of[has_word]
    keys = mix(byte_ranges(data, starts, ends) ^ mix(of.astype(np.uint64), 9))
    new = np.zeros(len(keys), bool)
    new[np.unique(keys, return_index=True)[1]] = True
    out["n_dup_lines"] = per_doc(~new, of, n)

    at, h = w.windows(3)
    _, inverse, times = np.unique(mix(h ^ mix(w.doc[at].astype(np.uint64), 11)), return_inverse=True, return_counts=True)
    repeated = covered(at[times[inverse] > 1], 3, len(w.starts)) if len(at) else np.zeros(len(w.starts), bool)
    out["n_repeat_words"] = per_doc(repeated, w.doc, n)
    return out


class Pieces:
    """Tokens of single words, found once: for each word the ids, and how
    many are fallback bytes."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = self.model.get_piece_size()
        self.is_byte = np.array([self.model.is_byte(i) for i in range(size)])
        self.forget()

    def forget(self) -> None:
        self.number: dict[int, int] = {}
        self.ids = np.zeros(1 << 16, np.int32)
        self.first = np.zeros(1 << 14, np.int64)
        self.used = 0

    def of(self, w: Words) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of all words in order, and the text of each token."""
        distinct, at, inverse = np.unique(w.hashes, return_index=True, return_inverse=True)
        if len(self.number) + len(distinct) > MOST_WORDS:
            self.forget()
        keys = distinct.tolist()
        known, raw = self.number, w.data.tobytes()
        starts, ends = w.starts[at].tolist(), w.ends[at].tolist()
        fresh = [i for i, k in enumerate(keys) if k not in known]
        if fresh:
            self._add([keys[i] for i in fresh], self.model.encode([raw[starts[i] : ends[i]].decode() for i in fresh], num_threads=1))
        numbers = np.array([self.number[k] for k in keys], np.int64)[inverse]
        first = self.first[numbers]
        lengths = self.first[numbers + 1] - first
        ends = np.cumsum(lengths)
        total = int(ends[-1]) if len(ends) else 0
        place = np.arange(total) - np.repeat(ends - lengths, lengths) + np.repeat(first, lengths)
        return self.ids[place], np.repeat(w.doc, lengths)

    def _add(self, keys: list[int], encoded: list[list[int]]) -> None:
        n, more = len(self.number), sum(map(len, encoded))
        self.number.update(zip(keys, range(n, n + len(keys)), strict=True))
        self.first = _room(self.first, n + len(keys) + 1)
        self.ids = _room(self.ids, self.used + more)
        self.ids[self.used : self.used + more] = np.fromiter(chain.from_iterable(encoded), np.int32, more)
        self.first[n + 1 : n + len(keys) + 1] = self.used + np.cumsum(np.fromiter(map(len, encoded), np.int64, len(encoded)))
        self.used += more


def _room(array: np.ndarray, size: int) -> np.ndarray:
    return array if size <= len(array) else np.concatenate([array, np.zeros(max(size, 2 * len(array)) - len(array), array.dtype)])


def token_measures(w: Words, pieces: Pieces) -> dict[str, np.ndarray]:
    n = len(w.counts)
    ids, doc = pieces.of(w)
    tokens = per_doc(np.ones(len(doc), np.int64), doc, n)
    byte = per_doc(pieces.is_byte[ids], doc, n)
    keys, times = np.unique(doc.astype(np.int64) << 32 | ids, return_counts=True)
    of = keys >> 32
    share = times / np.maximum(tokens, 1)[of]
    entropy = np.bincount(of, weights=-share * np.log2(share), minlength=n) if len(of) else np.zeros(n)
    return {"n_tokens": tokens, "byte_share": byte / np.maximum(tokens, 1), "token_entropy": np.round(np.abs(entropy), 9)}


def scripts_of(data: np.ndarray, offsets: np.ndarray) -> list[str]:
    """The script with most letters of each text. Texts without a lead byte
    of U+0240 or more can only be Latin, and are not decoded."""
    far = np.concatenate([[0], np.cumsum(data >= 0xC9)])[offsets]
    latin = np.concatenate([[0], np.cumsum(((data | 32) >= 0x61) & ((data | 32) <= 0x7A) | (data >= 0xC3) & (data < 0xC9))])[offsets]
    out = ["latin" if n else "other" for n in np.diff(latin).tolist()]
    for i in np.flatnonzero(np.diff(far)).tolist():
        points = np.frombuffer(data[offsets[i] : offsets[i + 1]].tobytes().decode().encode("utf-32-le"), np.uint32)
        counts = {name: sum(int(((points >= a) & (points <= b)).sum()) for a, b in spans) for name, spans in BLOCKS.items()}
        best = max(counts, key=counts.get)
        out[i] = best if counts[best] else "other"
    return out


def judged(data: np.ndarray, offsets: np.ndarray, langs: list, pieces: Pieces, languages: dict[str, Band], scripts: dict[str, Band]) -> dict:
    w = words_of(data, offsets, BLANK_WORDS)
    got = base_counts(w, offsets) | token_measures(w, pieces)
    got["base_failed"] = (got["n_words"] < LEAST_WORDS) | (100 * got["n_repeat_words"] > MOST_REPEATED * got["n_words"])
    got["chars_per_token"] = got["word_chars"] / np.maximum(got["n_tokens"], 1)
    script = scripts_of(data, offsets)
    bands = [languages.get(lang) or scripts.get(s) or scripts["other"] for lang, s in zip(langs, script, strict=True)]
    limits = np.array([(b.least_chars, b.most_chars, b.most_bytes, b.least_spread) for b in bands]).reshape(-1, 4)
    spread = got["token_entropy"] / np.log2(np.clip(got["n_tokens"], 2, 1 << 11))
    good = (got["chars_per_token"] >= limits[:, 0]) & (got["chars_per_token"] <= limits[:, 1]) & (got["byte_share"] <= limits[:, 2]) & (spread >= limits[:, 3])
    return got | {"kept": good & ~got["base_failed"], "script": script}


def _start(lang: str | None, vocab: str, languages: dict[str, Band], scripts: dict[str, Band]):
    import public_tokenizers

    pieces = per_process(f"pieces:{vocab}", lambda: Pieces(public_tokenizers.path(vocab)))

    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        langs = part.column(part.schema.get_field_index(lang)).to_pylist() if lang else [None] * (len(offsets) - 1)
        return judged(data, offsets, langs, pieces, languages, scripts)

    return measure


def score(docs: DataFrame, text: str = "text", lang: str | None = "lang", vocab: str = VOCABULARY, languages: dict[str, Band] = LANGUAGES, scripts: dict[str, Band] = SCRIPTS, keep: list[str] | None = None) -> DataFrame:
    """Add the measures, base_failed and kept to each row of docs."""
    return annotate(docs, text, RULES, lambda: _start(lang, vocab, languages, scripts), keep, reads=[lang] if lang else None, limit=CHUNK_BYTES)


def passing(docs: DataFrame, text: str = "text", lang: str | None = "lang", vocab: str = VOCABULARY, languages: dict[str, Band] = LANGUAGES, scripts: dict[str, Band] = SCRIPTS) -> DataFrame:
    """The rows of docs that pass, unchanged."""

    def start():
        measure = _start(lang, vocab, languages, scripts)
        return lambda part, data, offsets: measure(part, data, offsets)["kept"]

    return select_rows(docs, text, start)

"""URL filter: host rules, then a weighted vocabulary found by one automaton.

Rules come first; where none fits, an Aho-Corasick automaton counts the terms
of a strict and a soft list in host and path. A term counts only between
boundaries, that is, where neither neighbour is a letter, a digit or a
non-ASCII character. One strict term, or several distinct soft ones, block.

Defined results: a null URL, or one without "://", has an empty host and path
and is allowed. Repeated rows are judged alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Fixed values of the contract: verdict, host and path prefix of each rule.
RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))

#: Terms in the four languages of the paths, without accents, as urls have
#: them. Strict: words that hardly stand in the address of anything else.
STRICT = (
    # adult
    *("porn", "porno", "pornos", "xxx", "sex", "sexe", "sexo", "sexcam", "hentai", "escort", "escorts", "camgirl", "camgirls", "adult", "milf", "nudes", "erotik", "erotique", "erotico", "nackt"),
    # gambling
    *("casino", "casinos", "kasino", "roulette", "baccarat", "blackjack", "spielothek", "sportwetten", "tragamonedas"),
    # drugs sold without prescription
    *("viagra", "cialis", "levitra", "tramadol", "xanax"),
    # malware and stolen software
    *("warez", "keygen", "keygens", "malware", "phishing", "ransomware"),
)
#: Soft: words that good addresses have too, but seldom several unlike ones.
SOFT = (
    *("free", "win", "bonus", "cheap", "deal", "track", "click", "ads", "spam", "farm", "replica", "prize", "winner"),
    *("bet", "bets", "betting", "poker", "slots", "jackpot", "bingo", "lotto", "lottery"),
    *("pills", "pharma", "loan", "payday", "crypto", "forex", "torrent", "torrents", "crack", "nude", "dating"),
    *("gratis", "kostenlos", "billig", "gewinn", "gewinnspiel", "wetten", "kredit", "pillen", "werbung"),
    *("gratuit", "gratuite", "gagner", "pari", "pilules", "rencontre", "rencontres", "publicite"),
    *("apuestas", "ganar", "dinero", "premio", "barato", "pastillas", "prestamo", "citas", "anuncios"),
)
SOFT_LIMIT = 2

VERDICT = T.StructType(
    [T.StructField(n, T.StringType()) for n in ("host", "path", "rule", "verdict")] + [T.StructField(n, T.LongType()) for n in ("strict_hits", "soft_hits", "soft_distinct")]
)


def parts_of(url: str | None) -> tuple[str, str]:
    """Host, with A-Z lower-cased, and path of a URL."""
    _, mark, rest = (url or "").partition("://")
    if not mark:
        return "", ""
    for end in "?#":
        rest = rest.partition(end)[0]
    host, slash, path = rest.partition("/")
    return lower(host), slash + path


def lower(text: str) -> str:
    return text.lower() if text.isascii() else "".join(c.lower() if "A" <= c <= "Z" else c for c in text)


class Vocabulary:
    def __init__(self, strict: tuple[str, ...], soft: tuple[str, ...]):
        import ahocorasick

        self.found = ahocorasick.Automaton()
        for term in {*strict, *soft}:
            self.found.add_word(term, (len(term), term in strict, term))
        self.found.make_automaton()

    def hits(self, text: str) -> tuple[int, int, int]:
        """Strict hits, soft hits, distinct soft terms."""
        strict, soft, kinds = 0, 0, set()
        for end, (n, is_strict, term) in self.found.iter(text):
            if end >= n and joins(text[end - n]) or end + 1 < len(text) and joins(text[end + 1]):
                continue
            if is_strict:
                strict += 1
            else:
                soft += 1
                kinds.add(term)
        return strict, soft, len(kinds)


def joins(c: str) -> bool:
    """Whether a neighbour makes a term part of a longer word."""
    return c.isalnum() if c < "\x80" else True


def rule_for(host: str, path: str, rules: tuple) -> tuple[str, str] | None:
    fits = [(h + p, verdict) for verdict, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fits, key=lambda r: len(r[0])) if fits else None


def judge(pages: DataFrame, url: str = "url", rules: tuple = RULES, strict: tuple[str, ...] = STRICT, soft: tuple[str, ...] = SOFT, soft_limit: int = SOFT_LIMIT, keep: list[str] | None = None) -> DataFrame:
    """Add host, path, rule, verdict and hit counts to each row. An added
    column replaces one of pages that has its name."""
    kept = [c for c in (pages.columns if keep is None else keep) if c not in VERDICT.names]
    taken = pages.select(*dict.fromkeys([*kept, url]))
    out = T.StructType([f for f in taken.schema if f.name in kept] + list(VERDICT))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Vocabulary(strict, soft)
        for batch in batches:
            rows = []
            for u in batch.column(batch.schema.get_field_index(url)).to_pylist():
                host, path = parts_of(u)
                rule = rule_for(host, path, rules)
                hits = words.hits(host + lower(path))
                own = "block" if hits[0] or hits[2] >= soft_limit else "allow"
                rows.append((host, path, rule and rule[0], rule[1] if rule else own, *hits))
            cols = list(zip(*rows, strict=True)) or [[]] * len(VERDICT)
            kinds = [pa.string()] * 4 + [pa.int64()] * 3
            yield pa.RecordBatch.from_arrays(
                [batch.column(batch.schema.get_field_index(c)) for c in kept] + [pa.array(c, k) for c, k in zip(cols, kinds, strict=True)],
                names=[*kept, *VERDICT.names],
            )

    return taken.mapInArrow(run, out)

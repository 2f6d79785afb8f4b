"""Column expressions shared by the methods; each has a DuckDB twin with the same result."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN_SPLIT = "[^a-zà-ÿß]+"
ACCENTED, PLAIN = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿß", "aaaaaaceeeeiiiinooooouuuuyys"
CATALOG = "cast(substring(source, 4) as int) % 5"


def tokens(text: str | Column = "text") -> Column:
    """Lower-cased words; runs of anything but letters separate."""
    c = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(F.lower(c), TOKEN_SPLIT), lambda t: t != "")


def sql_tokens(text: str = "text") -> str:
    return f"list_filter(string_split_regex(lower({text}), '{TOKEN_SPLIT}'), lambda t: t <> '')"


def hash60(text: str) -> Column:
    """The leading 60 bits of the md5 of a string expression, as bigint."""
    return F.expr(f"cast(conv(substring(md5({text}), 1, 15), 16, 10) as bigint)")


def sql_hash60(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::bigint"


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once, however often and in whatever loop the body names it."""
    return F.transform(F.array(value), body)[0]


def run_hash(hashes: Column, start: Column, k: int) -> Column:
    """The hash of ``k`` words from ``start`` (from 0) on, of an array of the words' own hashes."""
    return F.xxhash64(*[F.get(hashes, start + j) for j in range(k)])


def word_hashes(words: Column) -> Column:
    return F.transform(words, lambda w: F.xxhash64(w))


def shingles(words: Column, k: int = 5) -> Column:
    """Distinct runs of k words as 64-bit hashes; none for shorter texts. Each word is hashed once."""
    def runs(h: Column) -> Column:
        spots = F.when(F.size(h) >= k, F.sequence(F.lit(0), F.size(h) - k)).otherwise(F.array().cast("array<int>"))
        return F.array_distinct(F.transform(spots, lambda i: run_hash(h, i, k)))

    return let(word_hashes(words), runs)


def normalize_name(name: str | Column) -> Column:
    """Lower case, accents folded, everything but letters and digits to one blank, trimmed."""
    c = F.col(name) if isinstance(name, str) else name
    return F.trim(F.regexp_replace(F.translate(F.lower(c), ACCENTED, PLAIN), "[^a-z0-9]+", " "))


def sql_normalize_name(name: str) -> str:
    return f"trim(regexp_replace(translate(lower({name}), '{ACCENTED}', '{PLAIN}'), '[^a-z0-9]+', ' ', 'g'))"

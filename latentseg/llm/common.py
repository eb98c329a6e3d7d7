"""What several operators share: the word class, ASCII folding, row keys."""

from __future__ import annotations

from collections.abc import Collection

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A word is a run of characters other than these six.
SPACES = " \t\n\x0b\x0c\r"
SPACE_RUN = r"[\x20\x09-\x0D]+"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def whole(text: str | Column) -> Column:
    """The text, with null read as empty."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def named(column: str) -> Column:
    """A column by its exact name, dots and all."""
    return F.col("`" + column.replace("`", "``") + "`")


def beside(docs: DataFrame, drop: Collection[str] = (), alias: str = "row") -> Column:
    """The columns of docs as one struct, so that a stage's own columns beside it cannot clash with them; those named (in any case) in `drop` are left out."""
    gone = {c.lower() for c in drop}
    return F.struct(*[named(c) for c in docs.columns if c.lower() not in gone]).alias(alias)


def words_of(text: Column) -> Column:
    """Array of words; empty for a null, an empty or an all-space text."""
    trimmed = F.btrim(text, F.lit(SPACES))
    return F.when(F.length(trimmed) > 0, F.split(trimmed, SPACE_RUN)).otherwise(F.array().cast("array<string>"))


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def identity_of(id_col: str, text_col: str) -> Column:
    """A string that seeds per-row hashes: the id, or for rows without one the digest of their text."""
    return F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("text:"), F.md5(whole(text_col))))


def hex_digest(salt: str, identity: Column) -> Column:
    """32 hex digits that depend on salt and row alone: the same in every engine and for every layout."""
    return F.md5(F.concat(F.lit(f"{salt}:"), identity))


def hex_to_long(digest: Column, start: int, digits: int) -> Column:
    """`digits` (at most 12) hex digits of a digest from 1-based `start`, as a number."""
    return F.conv(F.substring(digest, start, digits), 16, 10).cast("long")


def buckets_for(rows: int, least: int = 256, per_bucket: int = 50_000) -> int:
    """A power of two: enough buckets that each holds about `per_bucket` rows at most, and never under `least`."""
    n = least
    while n * per_bucket < rows:
        n *= 2
    return n


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


_BLANK = np.zeros(256, bool)
_BLANK[[ord(c) for c in SPACES]] = True
#: A number for each byte (A-Z as a-z) and an odd one for each place in a word.
_BYTE = mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BYTE[65:91] = _BYTE[97:123]
_place = np.empty(0, np.uint64)
#: Bytes hashed at a time; a window ends behind a blank.
WINDOW = 1 << 17


def _places(n: int) -> np.ndarray:
    global _place
    if len(_place) < n:
        _place = mixed(np.arange(1, max(n, 256) + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)) | np.uint64(1)
    return _place


def hashed_words(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, starts) of the words in a byte array: each byte's number times that of its place, added up over the word and mixed. Array operations on
    windows, so nothing is kept but the result; only a word longer than a window widens it."""
    hashes, starts = [np.empty(0, np.uint64)], [np.empty(0, np.int64)]
    at = 0
    while at < len(raw):
        end = at + WINDOW
        while end < len(raw):
            cut = np.flatnonzero(_BLANK[raw[max(at, end - WINDOW) : end]])
            if len(cut):
                end = max(at, end - WINDOW) + int(cut[-1]) + 1
                break
            end += WINDOW
        part = raw[at:end]
        own = np.flatnonzero(~_BLANK[part])
        if len(own):
            first = np.concatenate([[0], np.flatnonzero(np.diff(own) > 1) + 1])
            size = np.diff(np.append(first, len(own)))
            place = _places(int(size.max()))[np.arange(len(own)) - np.repeat(first, size)]
            hashes.append(mixed(np.add.reduceat(_BYTE[part[own]] * place, first)))
            starts.append(own[first] + at)
        at = end
    return np.concatenate(hashes), np.concatenate(starts)

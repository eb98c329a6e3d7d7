"""Text units: lines, chunks, snippets, noise, derived varieties, page text. Built-in functions but for Unicode normalisation."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .cluster import lean, slices
from .io import spread

#: A chunk: letters or symbols with an optional space before, or white space. Chunks of a text put together are the text.
CHUNK = r" ?\p{L}+| ?[^\s\p{L}]+|\s+"
LETTERS = "abcdefghijklmnopqrstuvwxyz"
GREEK = "αβγδεζηθικλμνξοπρστυφχψωϊϋ"
MARKED, PLAIN = "àâäáçèéêëíîïñóôöùúûüÀÂÄÁÇÈÉÊËÍÎÏÑÓÔÖÙÚÛÜ", "aaaaceeeeiiinooouuuuAAAACEEEEIIINOOOUUUU"
#: (low, high, name) of line lengths in characters.
BANDS = [(0, 50, "000-050"), (51, 100, "051-100"), (101, 150, "101-150"), (151, 250, "151-250"), (251, 500, "251-500"), (501, 999, "501-999"), (1000, 2**31 - 1, "1000-")]
#: Spelling rules of the derived varieties: language -> for each variety the replacements it makes. The first variety of each is the standard.
VARIETIES = {
    "en": [[], [("er", "re"), ("th", "d")], [("ti", "ci"), ("ou", "o")], [("ing", "in"), ("an", "en")]],
    "fr": [[], [("eau", "o"), ("ch", "sh")], [("qu", "k"), ("ou", "u")], [("tion", "sion"), ("en", "an")]],
    "de": [[], [("ich", "isch"), ("ei", "ai")], [("st", "scht"), ("sch", "sh")], [("ung", "ig"), ("er", "a")]],
    "es": [[], [("ci", "si"), ("ll", "y")]],
}
SHARE = 60  # per cent of words that a variety respells


def hash8(text: Column) -> Column:
    """The first eight hex digits of md5 as a number: equal in every engine."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def bucket(text: Column, n: int = 5) -> Column:
    """0 test, 1 validation, others training; equal texts never straddle a split."""
    return F.pmod(hash8(text), F.lit(n)).cast("int")


def lines(docs: DataFrame, label_col: str = "lang", text_col: str = "text") -> DataFrame:
    """(doc_id, line_no, label, source, text, n_chars, bucket): trimmed, non-empty lines. Null texts have none."""
    df = docs.select("doc_id", F.col(label_col).alias("label"), "source", F.posexplode(F.split(text_col, "\n", -1)).alias("line_no", "raw"))
    df = df.select("doc_id", "line_no", "label", "source", F.trim("raw").alias("text")).where("text <> ''")
    return df.withColumns({"n_chars": F.length("text").cast("long"), "bucket": bucket(F.col("text"))})


def pretokenize(text: Column, kind: str = "regex", prefix_space: bool = False, unit: str = "codepoint") -> Column:
    """Array of chunks that no token crosses: none (the whole text), space, or regex. prefix_space: a text begins with a space. unit byte: chunks are found in the text, then each of
    their UTF-8 bytes becomes one character."""
    if prefix_space:
        text = F.when(text.startswith(" ") | (text == ""), text).otherwise(F.concat(F.lit(" "), text))
    chunks = F.array(text) if kind == "none" else F.regexp_extract_all(text, F.lit(CHUNK if kind == "regex" else r" ?\S+|\s+"), 0)
    return F.transform(chunks, lambda c: F.decode(F.encode(c, "UTF-8"), "ISO-8859-1")) if unit == "byte" else chunks


def units(text: Column, mode: str = "codepoint") -> Column:
    """A text's characters: code points, or its UTF-8 bytes as numbers in hex."""
    return F.split(text, "") if mode == "codepoint" else F.regexp_extract_all(F.hex(F.encode(text, "UTF-8")), F.lit(".."), 0)


def detokenize(tokens: Column, unit: str = "codepoint") -> Column:
    joined = F.array_join(tokens, "")
    return F.decode(F.encode(joined, "ISO-8859-1"), "UTF-8") if unit == "byte" else joined


def chunk_counts(df: DataFrame, label_col: str = "label", text_col: str = "text", kind: str = "regex", prefix_space: bool = False, unit: str = "codepoint") -> DataFrame:
    """(label, chunk, n): equal chunks are added up before anything is computed on them. Chunks are whole, however long."""
    pieces = df.select(F.col(label_col).alias("label"), F.explode(pretokenize(F.col(text_col), kind, prefix_space, unit)).alias("chunk")).where("chunk <> ''")
    return pieces.groupBy("label", "chunk").agg(F.count(F.lit(1)).alias("n"))


def short_words(df: DataFrame, label_col: str = "lang", text_col: str = "text", most: int = 6) -> DataFrame:
    """(label, chunk, n): lower-case letter runs of at most `most` letters, for brute-force comparison."""
    w = df.select(F.col(label_col).alias("label"), F.explode(F.regexp_extract_all(F.lower(text_col), F.lit(r"\p{L}+"), 0)).alias("chunk"))
    return w.where(F.length("chunk") <= most).groupBy("label", "chunk").agg(F.count(F.lit(1)).alias("n"))


def snippets(line_df: DataFrame, length: int = 20) -> DataFrame:
    """Adds snippet: `length` characters from a place that the line's ids determine."""
    start = F.pmod(hash8(F.concat_ws(":", F.col("doc_id").cast("string"), F.col("line_no").cast("string"))), F.greatest(F.lit(1).cast("long"), F.col("n_chars") - length + 1)) + 1
    return line_df.withColumn("start", start).withColumn("snippet", F.expr(f"substring(text, cast(start as int), {length})"))


def sample_j(line_df: DataFrame, j: int, seed: int) -> DataFrame:
    """j lines for each label, by the order of a seeded digest; a rank filter keeps the sort partial."""
    from pyspark.sql import Window

    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"), F.col("line_no").cast("string")))
    w = Window.partitionBy("label").orderBy("k", "doc_id", "line_no")
    return line_df.withColumn("k", key).withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= j).drop("k", "rn")


def corrupt(line_df: DataFrame, per_mille: int, seed: int = 1) -> DataFrame:
    """Replaces non-space characters whose digest falls under the rate by a letter taken from the same digest."""

    def one(ch: Column, i: Column) -> Column:
        h = hash8(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"), F.col("line_no").cast("string"), i.cast("string")))
        letter = F.substring(F.lit(LETTERS), F.pmod(F.floor(h / 1000), F.lit(26)).cast("int") + 1, F.lit(1))
        return F.when((F.trim(ch) != "") & (F.pmod(h, F.lit(1000)) < per_mille), letter).otherwise(ch)

    return line_df.withColumn("text", F.array_join(F.transform(F.split("text", ""), one), ""))


def corrupt_each(line_df: DataFrame, rates: tuple[int, ...], seed: int = 1) -> DataFrame:
    """The texts that corrupt() gives for each of the rates, told apart by per_mille. A character's digest is the same at every rate, so it is taken once for all, in an Arrow kernel."""
    letters = np.frombuffer(LETTERS.encode("utf-32-le"), np.uint32)
    kind = T.StructType([*line_df.schema.fields, T.StructField("per_mille", T.IntegerType())])
    names = line_df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number: list[bytes] = []
        for b in slices(batches):
            made: list[list[str | None]] = [[] for _ in rates]
            for t, key in zip(b.column("text").to_pylist(), b.column("_key").to_pylist(), strict=True):
                if t is None:
                    for out in made:
                        out.append(None)
                    continue
                points, key = np.frombuffer(t.encode("utf-32-le"), np.uint32), key.encode()
                number += [b":%d" % i for i in range(len(number), len(points))]
                at = np.flatnonzero(points != 32)
                h = np.frombuffer(b"".join([hashlib.md5(key + number[i], usedforsecurity=False).digest() for i in at.tolist()]), ">u4")[::4].astype(np.int64)
                low, letter = h % 1000, letters[h // 1000 % 26]
                for rate, out in zip(rates, made, strict=True):
                    hit, noisy = low < rate, points.copy()
                    noisy[at[hit]] = letter[hit]
                    out.append(noisy.tobytes().decode("utf-32-le"))
            for rate, out in zip(rates, made, strict=True):
                own = [pa.array(out, pa.string()) if c == "text" else b.column(c) for c in names]
                yield pa.RecordBatch.from_arrays([*own, pa.array([rate] * b.num_rows, pa.int32())], names=[*names, "per_mille"])

    keyed = line_df.withColumn("_key", F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"), F.col("line_no").cast("string")))
    return spread(keyed).mapInArrow(lean(run), kind)


def permutation(k: int, alphabet: str = LETTERS) -> str:
    """Letters of a cipher: the alphabet in the order of digests; cipher 0 is plain."""
    return LETTERS if k == 0 and alphabet == LETTERS else "".join(sorted(alphabet, key=lambda c: hashlib.md5(f"{k}:{c}".encode()).hexdigest()))


def cipher(text: Column, k: int, alphabet: str = LETTERS) -> Column:
    return F.translate(F.lower(text), LETTERS, permutation(k, alphabet))


def _respeller(v: int, rules: list[tuple[str, str]]):
    def respell(word: Column) -> Column:
        out = word
        for a, b in rules:
            out = F.replace(out, F.lit(a), F.lit(b))
        return F.when(F.pmod(hash8(F.concat(F.lit(f"{v}:"), word)), F.lit(100)) < SHARE, out).otherwise(word)

    return respell


def dialects(line_df: DataFrame) -> DataFrame:
    """(..., label such as fr-2, family): a line's digest picks its variety; each variety respells a hashed share of the words."""
    counts = {k: len(v) for k, v in VARIETIES.items()}
    n = F.coalesce(*[F.when(F.col("label") == k, F.lit(v)) for k, v in counts.items()], F.lit(1))
    df = line_df.withColumn("variety", F.pmod(hash8(F.concat(F.lit("variety:"), F.col("text"))), n).cast("int"))
    text = F.col("text")
    for lang, varieties in VARIETIES.items():
        for v, rules in enumerate(varieties):
            if not rules:
                continue

            text = F.when((F.col("label") == lang) & (F.col("variety") == v), F.array_join(F.transform(F.split("text", " "), _respeller(v, rules)), " ")).otherwise(text)
    return df.withColumn("new", text).select(*[c for c in line_df.columns if c not in ("text", "label")], F.col("new").alias("text"), F.col("label").alias("family"), F.concat_ws("-", "label", "variety").alias("label"))


def no_marks(text: Column) -> Column:
    return F.translate(text, MARKED, PLAIN)


def band(n: Column) -> Column:
    out = F.lit(None).cast("string")
    for lo, hi, name in BANDS:
        out = F.when((n >= lo) & (n <= hi), name).otherwise(out)
    return out


def html_to_text(html: Column) -> Column:
    """Visible text: scripts, styles, comments and tags become spaces, the five usual entities characters, runs of space one."""
    t = F.regexp_replace(html, r"(?s)<!--.*?-->", " ")
    t = F.regexp_replace(t, r"(?s)<script.*?</script>", " ")
    t = F.regexp_replace(t, r"(?s)<style.*?</style>", " ")
    t = F.regexp_replace(t, r"<[^>]*>", " ")
    for a, b in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        t = F.replace(t, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(t, r"\s+", " "))


def page_lang(html: Column) -> Column:
    return F.regexp_extract(html, r'<html lang="([a-z]+)"', 1)


def normalize(form: str = "NFC"):
    """Unicode normal form; Spark has no built-in for it."""
    @F.pandas_udf("string")
    def norm(s: pd.Series) -> pd.Series:
        return s.str.normalize(form)

    return norm

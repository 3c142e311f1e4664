"""Text to paragraphs, sentences and words, as Column expressions (no shuffle, no Python worker)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Stands for a cut; it can't occur in text that survived XML or JSON.
CUT = "\x01"
TERMINATORS = ".!?"
SPACE = r"[ \t\r\f]+"
#: Unicode's space separators, which go at either end of a piece.
BLANKS = " \u00a0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u202f\u205f\u3000"


def h(x: Column) -> Column:
    """Portable hash: the first 8 hexadecimal digits of the md5, as a number."""
    return F.conv(F.substring(F.md5(x.cast("string").cast("binary")), 1, 8), 16, 10).cast("long")


def key(*parts: Column | str) -> Column:
    """Values joined by dashes, to be hashed."""
    return F.concat_ws("-", *(p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts))


def _full(pieces: Column) -> Column:
    # F.trim itself has two parameters: transform would hand it the place as the characters to trim
    return F.filter(F.transform(pieces, lambda x: F.trim(x, F.lit(BLANKS))), lambda x: F.length(x) > 0)


def split_paragraphs(text: Column, mode: str = "newline") -> Column:
    """Paragraph strings: cut at each line end, or at blank lines only."""
    if mode == "newline":
        return _full(F.split(text, "\n"))
    if mode == "blank_line":
        return _full(F.transform(F.split(text, r"\n[ \t\r]*\n\s*"), lambda p: F.regexp_replace(p, "\n", " ")))
    raise ValueError(f"mode {mode}")


def split_sentences(text: Column, terminators: str = TERMINATORS) -> Column:
    """Sentence strings: cut after a run of terminators that white space follows.

    A transcript whose marks were inserted by a model is cut at period or question mark alone.
    """
    return _full(F.split(F.regexp_replace(text, f"([{terminators}]+)[ \\t\\r\\f\\n]+", f"$1{CUT}"), CUT))


def count_words(text: Column) -> Column:
    return F.size(F.split(text, SPACE))


def words(text: Column) -> Column:
    """Distinct lower-case runs of letters."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(r"(\p{L}+)"), F.lit(1)))


def sentence_array(paragraphs: Column, terminators: str = TERMINATORS) -> Column:
    """Paragraphs to the array of (idx, text, n_tok, ends_para) of the whole document.

    Labels every sentence by whether it closes its paragraph: segmentation as one yes/no a sentence.
    """
    by = F.filter(F.transform(paragraphs, lambda p: split_sentences(p, terminators)), lambda s: F.size(s) > 0)
    flat = F.flatten(F.transform(by, lambda ss: F.transform(ss, lambda s, i: F.struct(s.alias("text"), (i == F.size(ss) - 1).alias("ends_para")))))
    return F.transform(flat, lambda s, i: F.struct(i.cast("int").alias("idx"), s["text"].alias("text"), count_words(s["text"]).alias("n_tok"), s["ends_para"].alias("ends_para")))


def with_sentences(df: DataFrame, text: str = "text", mode: str = "newline", terminators: str = TERMINATORS) -> DataFrame:
    """Adds ``sents`` and ``n_sent``; null text has none."""
    paragraphs = split_paragraphs(F.coalesce(F.col(text), F.lit("")), mode)
    return df.withColumn("sents", sentence_array(paragraphs, terminators)).withColumn("n_sent", F.size("sents"))


def exploded(corpus: DataFrame, *keep: str) -> DataFrame:
    """One row a sentence: doc_id, n_sent, the kept columns, idx, text, n_tok, ends_para."""
    return corpus.select("doc_id", "n_sent", *keep, F.inline("sents"))


def _swap(name: str, sign: str):
    return lambda p: F.replace(p, F.lit(name), F.lit(sign))


def html_paragraphs(html: Column) -> Column:
    """Paragraphs of an article: scripts, styles, menus, adverts and footers go first, then tags."""
    x = F.regexp_replace(html, r"(?s)<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<footer.*?</footer>|<!--.*?-->", "")
    x = F.regexp_replace(x, r'(?s)<div class="ad">.*?</div>', "")
    inside = F.regexp_extract(x, r"(?s)<article>(.*)</article>", 1)
    parts = F.slice(F.split(inside, "<p>"), 2, 1 << 30)
    bare = F.transform(parts, lambda p: F.regexp_replace(F.regexp_replace(p, r"(?s)<[^>]*>", " "), r"[ \t\r\n\f]+", " "))
    for name, sign in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        bare = F.transform(bare, _swap(name, sign))
    return _full(bare)


def render(sents: Column, boundary: Column) -> Column:
    """Text for readers: sentences joined by spaces, a line end after each boundary."""
    joined = F.zip_with(sents, boundary, lambda s, b: F.concat(s["text"], F.when(b, "\n").otherwise(" ")))
    return F.rtrim(F.regexp_replace(F.array_join(joined, ""), r"[ \n]+$", ""))


def segments(boundary: Column) -> Column:
    """Boundary flags to an array of (first, last); the last sentence always closes a segment."""
    n = F.size(boundary)
    ends = F.filter(F.sequence(F.lit(0), n - 1), lambda i: (i == n - 1) | F.get(boundary, i))
    return F.when(n > 0, F.transform(ends, lambda e, k: F.struct(F.when(k == 0, 0).otherwise(F.get(ends, k - 1) + 1).cast("int").alias("first"), e.cast("int").alias("last"))))

"""Sub-word tokens of a public vocabulary file, longest match first, and dictionary word segmentation."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


UNKNOWN = "[unk]"
#: Closes the last piece of a word in the public vocabulary files.
END = "</w>"


def _byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in byte-level vocabularies: itself if printable, else one from 256 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


LETTERS = _byte_letters()


BYTES = {c: b for b, c in LETTERS.items()}


def spelled(letters: str) -> str:
    """The word whose bytes the letters stand for."""
    return bytes(BYTES.get(c, 63) for c in letters).decode("utf-8", "replace")


def load_vocab(path: str) -> dict[str, int]:
    """Pieces and ids of a public vocabulary file (JSON of the tokenizers library) whose words end in a mark."""
    with open(path, encoding="utf-8") as f:
        vocab = json.load(f)["model"]["vocab"]
    if not any(p.endswith(END) for p in vocab):
        raise ValueError(f"{path} doesn't mark the ends of words")
    return vocab


def pieces_of(word: str, vocab: dict[str, int], longest: int = 16) -> list[str]:
    """Longest match first over the word's bytes, its end marked; one unknown piece if some byte has no piece."""
    letters = [LETTERS[b] for b in word.encode("utf-8", "surrogatepass")]
    out, at = [], 0
    while at < len(letters):
        for end in range(min(len(letters), at + longest), at, -1):
            p = "".join(letters[at:end]) + (END if end == len(letters) else "")
            if p in vocab:
                out.append(p)
                at = end
                break
        else:
            return [UNKNOWN + END]
    return out


def as_pieces(corpus: DataFrame, vocab: dict[str, int]) -> DataFrame:
    """The corpus with sub-words for words: each sentence's text is its pieces between spaces, n_tok their number.

    Packing, schedules, training and inference then count and read pieces, without a change of theirs.
    """
    shared = corpus.sparkSession.sparkContext.broadcast(vocab)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        memo: dict[str, str] = {}

        def of(word: str) -> str:
            if word not in memo:
                if len(memo) > 200_000:
                    memo.clear()
                memo[word] = " ".join(pieces_of(word, shared.value))
            return memo[word]

        for pdf in frames:
            yield pdf.assign(pieces=[[" ".join(map(of, s)) for s in ss] for ss in pdf.pieces])

    words = F.transform("sents", lambda s: F.regexp_extract_all(F.lower(s["text"]), F.lit(r"(\p{L}+|\p{N}+|[^\s\p{L}\p{N}])"), F.lit(1)))
    rows = corpus.withColumn("pieces", words)
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" if f.name != "pieces" else "pieces array<string>" for f in rows.schema)
    got = rows.mapInPandas(run, kinds)
    sents = F.zip_with("sents", "pieces", lambda s, x: F.struct(s["idx"].alias("idx"), x.alias("text"), F.size(F.split(x, " ")).alias("n_tok"), s["ends_para"].alias("ends_para")))
    return got.withColumn("sents", sents).drop("pieces")


def encode(corpus: DataFrame, vocab: dict[str, int]) -> DataFrame:
    """Documents with sentences to (doc_id, toks array of each sentence's piece ids)."""
    shared = corpus.sparkSession.sparkContext.broadcast(vocab)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            yield pd.DataFrame({"doc_id": pdf.doc_id, "toks": [[[shared.value.get(p, 0) for p in s.split()] for s in ss] for ss in pdf.texts]})

    texts = as_pieces(corpus, vocab).select("doc_id", F.transform("sents", lambda s: s["text"]).alias("texts"))
    return texts.mapInPandas(run, "doc_id long, toks array<array<int>>")


def word_segment(text: str, lexicon: set[str], longest: int = 12) -> list[str]:
    """Dictionary segmentation of text without spaces: longest match, single characters otherwise."""
    out = []
    for run in text.split():
        at = 0
        while at < len(run):
            end = next((e for e in range(min(len(run), at + longest), at + 1, -1) if run[at:e] in lexicon), at + 1)
            out.append(run[at:end])
            at = end
    return out


def segmented(df: DataFrame, lexicon: DataFrame, longest: int = 12, most: int = 1_000_000, col: str = "text") -> DataFrame:
    """Rows with ``words``: the text segmented by the words of ``lexicon`` (word), a checked broadcast."""
    if (n := lexicon.count()) > most:
        raise ValueError(f"a lexicon of {n} words is more than {most}")
    shared = df.sparkSession.sparkContext.broadcast({r.word for r in lexicon.select("word").collect()})

    @F.pandas_udf("array<string>")
    def cut(texts: pd.Series) -> pd.Series:
        return texts.map(lambda x: None if x is None else word_segment(x, shared.value, longest))

    return df.withColumn("words", cut(col))


def count_pieces(encoded: DataFrame) -> DataFrame:
    return encoded.select("doc_id", F.aggregate("toks", F.lit(0), lambda a, s: a + F.size(s)).alias("n"), F.size("toks").alias("sents"))

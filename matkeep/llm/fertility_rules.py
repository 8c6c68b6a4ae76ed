"""Quality rules: tokeniser fertility.

A public vocabulary is a yardstick of how ordinary a text is: prose of a language it knows takes few tokens for its
characters and spreads over many of them. Per text are measured characters per token, the share of bytes the piece
vocabulary can only spell out (byte fallback), and the entropy of the text's tokens. Bands for each language, or else
for the script most letters are of, reject what lies outside.

Tokens are counted word by word, so each distinct word is encoded once for a batch of texts and looked up after that.
"""

from __future__ import annotations

import base64
import math
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .lookup import Lookup
from .shared import sliced

#: Where the public vocabularies are, on the driver; the files' contents are sent to the executors.
TOKENIZERS = "/opt/tokenizers"
#: The characters that count as symbols.
SYMBOLS = "#*$%&|<>"
#: Fixed value: splits text before byte pairs are merged (letters, digits, other signs, white space).
SPLIT = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+"""


@dataclass(frozen=True)
class Band:
    """What a text must meet; token measures are asked only of texts of ``min_tokens`` tokens or more."""

    min_chars_per_token: float
    max_chars_per_token: float
    max_fallback: float
    min_entropy: float
    min_tokens: int = 64


#: By language where ``lang`` names one, else by script. Set wide: prose of rare words must pass.
BANDS = {
    "en": Band(1.75, 9.0, 0.05, 4.0),
    "de": Band(1.75, 9.0, 0.05, 4.0),
    "es": Band(1.70, 9.0, 0.05, 4.0),
    "fr": Band(1.60, 9.0, 0.05, 4.0),
    "latin": Band(1.35, 9.0, 0.20, 3.0),
    "cyrillic": Band(1.0, 9.0, 0.20, 3.0),
    "greek": Band(0.7, 9.0, 0.30, 3.0),
    "han": Band(0.4, 4.0, 0.70, 3.0),
    "other": Band(0.3, 9.0, 0.95, 2.5),
}

SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, kept boolean, script string, n_tokens long, chars_per_token double, fallback_share double, token_entropy double"
)


class Yardstick:
    """Tokens of words under a byte-pair vocabulary, each distinct word encoded once."""

    def __init__(self, ranks: dict[bytes, int], piece_chars: frozenset[str]):
        import tiktoken

        encode = tiktoken.Encoding("words", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.words = Lookup(lambda word: encode(" " + word.decode("utf-8", "replace")))
        self.piece_chars = piece_chars


def repeated_words(ids: np.ndarray, width: int = 5) -> int:
    """How many words stand in a window of ``width`` words that the text has twice or more."""
    n = len(ids)
    if n <= width:
        return 0
    dense = lambda values: np.unique(values, return_inverse=True)[1].reshape(-1)
    single = dense(ids)
    code, k = single, int(single.max()) + 1
    for i in range(1, width):  # exact: codes are made dense again before they could overflow
        code = code[:-1] * k + single[i:]
        if i < width - 1:
            code = dense(code)
    _, inverse, counts = np.unique(code, return_inverse=True, return_counts=True)
    twice = counts[inverse.reshape(-1)] > 1
    if not twice.any():
        return 0
    cover = np.zeros(n + 1, dtype=np.int64)
    cover[:-width][twice] += 1
    cover[width:][twice] -= 1
    return int((np.cumsum(cover)[:-1] > 0).sum())


def duplicate_lines(text: str) -> int:
    """Lines with a word that equal an earlier line."""
    lines = [x for x in text.split("\n") if x.encode("utf-8", "surrogatepass").split()] if "\n" in text else []
    return len(lines) - len(set(lines))


def script_of(text: str) -> str:
    """The script of most letters of the text; each distinct character is named once."""
    found: dict[str, int] = {}
    for c, n in Counter(text).items():
        if c.isascii():
            name = "latin" if c.isalpha() else ""
        else:
            named = unicodedata.name(c, "").partition(" ")[0].lower() if c.isalpha() else ""
            name = {"cjk": "han", "hiragana": "han", "katakana": "han"}.get(named, named if named in BANDS or not named else "other")
        if name:
            found[name] = found.get(name, 0) + n
    return max(sorted(found), key=found.__getitem__) if found else "other"


def entropy(tokens: np.ndarray) -> float:
    if not len(tokens):
        return 0.0
    counts = np.unique(tokens, return_counts=True)[1] / len(tokens)
    return float(-(counts * np.log2(counts)).sum()) + 0.0


def within_band(band: Band, n_tokens: int, per_token: float, fallback: float, bits: float) -> bool:
    if not n_tokens:
        return False
    if fallback > band.max_fallback:
        return False
    if n_tokens < band.min_tokens:
        return True
    return band.min_chars_per_token <= per_token <= band.max_chars_per_token and bits >= band.min_entropy


def load_ranks(folder: str) -> dict[bytes, int]:
    with open(f"{folder}/byte_bpe_multi_50k.tiktoken", "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def load_piece_chars(folder: str) -> frozenset[str]:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=f"{folder}/piece_bpe_32k.model")
    pieces = (model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i)))
    return frozenset(p for p in pieces if len(p) == 1) | {" ", "\t", "\n", "\r", "\x0b", "\x0c"}


def judge_documents(spark: SparkSession, docs: DataFrame, bands: dict[str, Band] | None = None, tokenizers: str = TOKENIZERS) -> DataFrame:
    """One row for each document with its counts, measures and verdict.

    ``base_failed``: fewer than 10 words, or over a fifth of them repeated. ``kept``: not base_failed and inside the
    band of the language named by ``lang``, else of the script. A null or blank text has no words and fails. Every row is
    judged alone, so repeated rows get the same verdict; a null doc_id is carried. Other columns are not read. The
    vocabularies sent to executors are about a megabyte whatever the input.
    """
    bands = bands or BANDS
    sent = spark.sparkContext.broadcast((load_ranks(tokenizers), load_piece_chars(tokenizers)))
    names = [f.name for f in pa_fields()]

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ruler = Yardstick(*sent.value)
        for ids, texts, langs in sliced(batches):
            rows = [measure(text.as_py() or "", lang.as_py(), ruler, bands) for text, lang in zip(texts, langs, strict=True)]
            columns = list(zip(*rows, strict=True)) or [[]] * (len(names) - 1)
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), *(pa.array(c, f.type) for c, f in zip(columns, pa_fields()[1:], strict=True))], names=names)

    return docs.select("doc_id", "text", "lang").mapInArrow(judge, SCHEMA)


def pa_fields() -> list[pa.Field]:
    kinds = {"long": pa.int64(), "boolean": pa.bool_(), "double": pa.float64(), "string": pa.string()}
    return [pa.field(n, kinds[k]) for n, k in (x.split() for x in SCHEMA.split(", "))]


def measure(text: str, lang: str | None, ruler: Yardstick, bands: dict[str, Band]) -> tuple:
    words = text.encode("utf-8", "surrogatepass").split()
    ids = ruler.words.ids(words)
    n, chars = len(words), len(text) - sum(map(text.count, " \t\n\v\f\r"))
    repeats = repeated_words(ids)
    tokens = ruler.words.gather(ids)
    per_token = chars / len(tokens) if len(tokens) else 0.0
    strange = set(text) - ruler.piece_chars
    # Of the bytes of the words, those of characters that the vocabulary spells byte by byte.
    fallback = sum(text.count(c) * len(c.encode("utf-8", "surrogatepass")) for c in strange) / max(1, sum(map(len, words))) if strange else 0.0
    bits, script = entropy(tokens), script_of(text)
    failed = n < 10 or 100 * repeats > 20 * n
    band = bands.get(lang) or bands.get(script) or bands["other"]
    kept = not failed and within_band(band, len(tokens), per_token, fallback, bits)
    symbols = sum(map(text.count, SYMBOLS))
    return n, chars, symbols, duplicate_lines(text), repeats, failed, kept, script, len(tokens), per_token, fallback, bits

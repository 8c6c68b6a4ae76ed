"""Encoding texts into the pieces of a public vocabulary, and decoding them.

An Aho-Corasick automaton over all pieces reads a text once; at each position it names, over its output links, every
piece that ends there, and each relaxes the best score of a segmentation up to that position (Viterbi). Characters
that no piece holds are spelled out in byte pieces, at a penalty that makes them a last resort.

A piece of such vocabularies has its space mark in front only, and none spans a line end, so the best segmentation
falls apart at these places without loss. Stretches between them are segmented once and looked up after that.

Scores are log probabilities. A vocabulary of merges has ranks in their place, which are none: the sum of ranks says
nothing of a text. Its pieces get log probabilities by their rank (Zipf), a fixed rule; nothing is trained.
"""

from __future__ import annotations

import math
import re
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .lookup import Lookup
from .shared import list_column, sliced

#: The vocabulary on the driver; its pieces and scores are sent to the executors.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: Fixed value: the sign that stands for a space inside pieces.
SPACE = "▁"
#: Stands for a literal space sign of the text inside the segmenter; no piece may hold it.
HIDDEN = "\x00"
#: Vocabularies give pieces they never want chosen a score below this.
UNUSED_SCORE = -1e8
#: Added to a rank before its logarithm is taken (the constant usual in the Zipf-Mandelbrot law).
RANK_SHIFT = 2.7
#: Each byte spelled out scores this much less than the lowest piece.
BYTE_PENALTY = 10.0

#: Longer stretches are held in flat arrays.
SHORT = 1_000
#: Score of what no segmentation reaches.
NEVER = -math.inf

ENCODED = "doc_id long, ids array<int>, n_ids long, n_byte_ids long, score double, round_trip boolean"


@dataclass(frozen=True)
class Pieces:
    """A vocabulary: ordinary pieces with scores, and the ids of the 256 byte pieces."""

    texts: list[str]
    ids: list[int]
    scores: list[float]
    byte_ids: list[int]
    size: int

    @property
    def splits_at_space(self) -> bool:
        return not any(SPACE in t.lstrip(SPACE) for t in self.texts)

    @property
    def splits_at_line(self) -> bool:
        return not any("\n" in t for t in self.texts)


def log_scores(scores: list[float]) -> list[float]:
    """Scores as they are, or by rank where they are the ranks of merges: whole numbers from zero down, each once or unused."""
    ranks = [-s for s in scores if s > UNUSED_SCORE]
    if not ranks or any(r < 0 or r != int(r) for r in ranks) or len(set(ranks)) < len(ranks):
        return scores
    return [s if s <= UNUSED_SCORE else -math.log(RANK_SHIFT - s) for s in scores]


def load_pieces(path: str = MODEL) -> Pieces:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    size = model.get_piece_size()
    plain = [i for i in range(size) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
    spelled = sorted((int(model.id_to_piece(i)[3:5], 16), i) for i in range(size) if model.is_byte(i))
    if len(spelled) != 256:
        raise ValueError("the vocabulary needs its 256 byte pieces")
    pieces = Pieces([model.id_to_piece(i) for i in plain], plain, log_scores([model.get_score(i) for i in plain]), [i for _, i in spelled], size)
    if any(HIDDEN in t for t in pieces.texts):
        raise ValueError("a piece holds the reserved sign")
    return pieces


class Segmenter:
    """Best segmentation of a text; of equal scores the one whose last piece is longest, at each position."""

    def __init__(self, pieces: Pieces):
        import ahocorasick

        self.automaton = ahocorasick.Automaton()
        for text, i, score in zip(pieces.texts, pieces.ids, pieces.scores, strict=True):
            self.automaton.add_word(text, (len(text), i, score))
        self.automaton.make_automaton()
        self.single = frozenset(t for t in pieces.texts if len(t) == 1)
        self.byte_ids = pieces.byte_ids
        self.byte_score = min(s for s in pieces.scores if s > UNUSED_SCORE) - BYTE_PENALTY
        self.score_of = np.zeros(pieces.size)
        self.score_of[pieces.ids] = pieces.scores
        self.score_of[pieces.byte_ids] = self.byte_score
        self.is_byte = np.zeros(pieces.size, dtype=bool)
        self.is_byte[pieces.byte_ids] = True
        inner = "[^ \n]" if pieces.splits_at_line else "[^ ]"
        self.stretches = re.compile(f"\n| *{inner}+| +").findall if pieces.splits_at_space else (lambda text: [text])
        self.words = Lookup(self.segment)
        table = [b""] * pieces.size
        for text, i in zip(pieces.texts, pieces.ids, strict=True):
            table[i] = text.replace(SPACE, " ").encode()
        for b, i in enumerate(pieces.byte_ids):
            table[i] = bytes([b])
        self.table = np.array(table, dtype=object)

    def segment(self, stretch: str) -> list[int]:
        """One stretch as it stands in the text, its spaces included."""
        marked = stretch.replace(SPACE, HIDDEN).replace(" ", SPACE)
        n = len(marked)
        if n <= SHORT and self.single.issuperset(marked):
            return self._segment_short(marked, n)
        # Flat arrays: a stretch may be a whole long text.
        best, back, chosen = array("d", [0.0]) + array("d", [NEVER]) * n, array("i", [0]) * (n + 1), array("i", [-1]) * (n + 1)
        lone = [i for i, c in enumerate(marked) if c not in self.single]
        at = 0
        for end, (length, piece, score) in self.automaton.iter(marked):
            while at < len(lone) and lone[at] < end:
                self._spell(best, back, chosen, lone[at], stretch)
                at += 1
            total = best[end + 1 - length] + score
            if total > best[end + 1] or (total == best[end + 1] and length > back[end + 1]):
                best[end + 1], back[end + 1], chosen[end + 1] = total, length, piece
        while at < len(lone):
            self._spell(best, back, chosen, lone[at], stretch)
            at += 1
        out: list[int] = []
        while n:
            piece = chosen[n]
            if piece >= 0:
                out.append(piece)
            else:
                out.extend(self.byte_ids[b] for b in reversed(stretch[n - 1].encode("utf-8", "surrogatepass")))
            n -= back[n]
        return out[::-1]

    def _segment_short(self, marked: str, n: int) -> list[int]:
        """The same where each character is a piece, so nothing is spelled. The score up to a character stands at its
        index, that of nothing at -1. The automaton names the longest piece first, so of equals the first stays."""
        best, chosen = [NEVER] * n, [None] * n
        best.append(0.0)
        for end, found in self.automaton.iter(marked):
            total = best[end - found[0]] + found[2]
            if total > best[end]:
                best[end], chosen[end] = total, found
        out, at = [], n - 1
        while at >= 0:
            length, piece, _ = chosen[at]
            out.append(piece)
            at -= length
        out.reverse()
        return out

    def _spell(self, best: array, back: array, chosen: array, at: int, stretch: str) -> None:
        total = best[at] + self.byte_score * len(stretch[at].encode("utf-8", "surrogatepass"))
        if total > best[at + 1]:
            best[at + 1], back[at + 1], chosen[at + 1] = total, 1, -1

    def encode(self, text: str) -> np.ndarray:
        return self.words.gather(self.words.ids(self.stretches(" " + text))) if text else np.zeros(0, dtype=np.int32)

    def decode(self, ids: np.ndarray) -> str:
        """Joins the pieces and takes off the space put before the text; bytes that are no UTF-8 become U+FFFD."""
        raw = b"".join(self.table[ids].tolist()) if len(ids) else b""
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


def encode_documents(spark: SparkSession, docs: DataFrame, model: str = MODEL) -> DataFrame:
    """doc_id, ids, n_ids, n_byte_ids, the segmentation's score, and whether decoding ids gives the text again.

    A null or empty text has no ids. Rows are encoded one by one, so repeated rows repeat; a null doc_id is carried.
    Other columns are not read. Texts are never cut. What is sent to executors is the vocabulary.
    """
    sent = spark.sparkContext.broadcast(load_pieces(model))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        segmenter = Segmenter(sent.value)
        for ids, texts in sliced(batches):
            found = [segmenter.encode(text.as_py() or "") for text in texts]
            same = [segmenter.decode(x) == (text.as_py() or "") for x, text in zip(found, texts, strict=True)]
            columns = [
                ids.cast(pa.int64()),
                list_column([x.astype(np.int32) for x in found], pa.int32()),
                pa.array([len(x) for x in found], pa.int64()),
                pa.array([int(segmenter.is_byte[x].sum()) for x in found], pa.int64()),
                pa.array([float(segmenter.score_of[x].sum()) for x in found], pa.float64()),
                pa.array(same, pa.bool_()),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "ids", "n_ids", "n_byte_ids", "score", "round_trip"])

    return docs.select("doc_id", "text").mapInArrow(encode, ENCODED)


def decode_ids(spark: SparkSession, encoded: DataFrame, model: str = MODEL) -> DataFrame:
    """doc_id and text of rows with doc_id and ids; null ids give an empty text, unknown ids raise."""
    sent = spark.sparkContext.broadcast(load_pieces(model))

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        segmenter = Segmenter(sent.value)
        for batch in batches:
            for start in range(0, batch.num_rows, 256):  # the texts of some rows at a time
                part = batch.slice(start, 256)
                texts = [segmenter.decode(np.array(ids.as_py() or [], dtype=np.int64)) for ids in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(decode, "doc_id long, text string")

"""Token counts by a count-only Viterbi search over a unigram vocabulary.

The pieces and scores of a local piece model are taken as a unigram vocabulary. Text is cut as a Metaspace
pre-tokenizer does: a space becomes the mark U+2581, a text without a leading mark gets one, and each mark
starts a new word. For each word an Aho-Corasick automaton lists all pieces by their end; dynamic
programming keeps only the best score and the number of pieces up to each end. Ties go as in the tokenizers
library's unigram model: of equal scores the piece that starts first stands; a character without a piece of
its own may be unknown, at ten below the lowest score, and then counts one piece for each of its UTF-8
bytes. Scores add up within a word in double precision.

A null text counts as empty and has no token; repeated rows give repeated results; an empty table gives an
empty one; further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
import public_tokenizers
import sentencepiece
from pyspark.sql import DataFrame

from . import textkit

MARK = "▁"
#: How far an unknown character lies below the lowest score, as in the library.
UNKNOWN = 10.0
_OPEN: dict[str, "Counts"] = {}


def vocabulary(model_file: str) -> list[tuple[str, float]]:
    model = sentencepiece.SentencePieceProcessor(model_file=model_file)
    return [(model.id_to_piece(i), model.get_score(i)) for i in range(model.get_piece_size())]


class Counts(dict):
    """Pieces of the words met so far (words without their leading mark)."""

    LIMIT = 500_000

    def __init__(self, pieces: list[tuple[str, float]]):
        self.automaton = ahocorasick.Automaton()
        for piece, score in pieces:
            self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        self.unknown = min(score for _, score in pieces) - UNKNOWN

    def __missing__(self, word: str) -> int:
        text = MARK + word
        n, unknown, none = len(text), self.unknown, float("-inf")
        best, count = [0.0] + [none] * n, [0] * (n + 1)
        ends = self.automaton.iter(text)
        end, value = next(ends, (n, None))
        for at in range(n):
            top, pieces, alone = none, 0, False
            while end == at and value is not None:  # longest first: the earliest start
                size, score = value
                start = at + 1 - size
                alone = alone or size == 1
                if best[start] + score > top:
                    top, pieces = best[start] + score, count[start] + 1
                end, value = next(ends, (n, None))
            if not alone and best[at] + unknown > top:
                top, pieces = best[at] + unknown, count[at] + len(text[at].encode("utf-8", "surrogatepass"))
            best[at + 1], count[at + 1] = top, pieces
        self[word] = count[n]
        return count[n]

    def of(self, text: str) -> int:
        if not text:
            return 0
        words = text.replace(" ", MARK).split(MARK)
        return sum(map(self.__getitem__, words[1:] if not words[0] else words))


def counter(model_file: str) -> Counts:
    if model_file not in _OPEN:
        _OPEN[model_file] = Counts(vocabulary(model_file))
    if len(_OPEN[model_file]) > Counts.LIMIT:
        _OPEN[model_file].clear()
    return _OPEN[model_file]


def token_counts(docs: DataFrame, model_file: str | None = None) -> DataFrame:
    """doc_id and n_tokens of every whole text."""
    model_file = model_file or public_tokenizers.path("piece_bpe_32k.model")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in textkit.slices(batches, "text"):
            known = counter(model_file)
            n = [known.of(t or "") for t in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(n, pa.int64())], names=["doc_id", "n_tokens"])

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, n_tokens long")


def op6_token_counts(spark, sf_dir: str) -> DataFrame:
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"))

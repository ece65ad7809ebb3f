"""Token counts by a unigram model, with dynamic programming shared over a trie.

A text's pre-tokens are its white-space separated words, each led by the vocabulary's word mark.  The tokens of a
pre-token are its best segmentation into vocabulary pieces (greatest sum of piece scores; ties: fewest pieces), characters outside
the vocabulary becoming their UTF-8 bytes.  The distinct pre-tokens of a batch are visited in sorted order, a depth-first
walk of their trie: the forward scores of a shared prefix are computed once and stay on a stack, and the count is read at
the terminal.  Counts then go back to documents by the words' hashes.

The vocabulary is a ``sentencepiece`` model file; its path is a parameter.  Files of byte-pair type hold merge ranks
instead of log probabilities; there a piece of rank r scores -ln(r + 1), as if by Zipf's law.

Defined cases: null and blank texts have no tokens; repeated rows are counted each; whole texts are counted.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import read_table
from boundpath.llm.textkernel import chunks, powers, mix, segment_sum, split_spans, word_bytes

WORD_MARK = "▁"
MEMORY_WORDS = 300_000
RESULT_SCHEMA = "doc_id bigint, n_words bigint, n_bytes bigint, n_tokens bigint"


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class UnigramVocabulary:
    """Pieces with scores, and a byte score for characters that no piece covers."""

    def __init__(self, scores: dict[str, float]):
        self.scores = scores
        self.longest = max(map(len, scores), default=1)
        self.byte_score = min(scores.values(), default=0.0) - 10.0

    @classmethod
    def load(cls, path: str) -> "UnigramVocabulary":
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        found = {}
        for i in range(sp.get_piece_size()):
            if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i)):
                found[sp.id_to_piece(i)] = sp.get_score(i)
        if found and min(found.values()) <= -1000:
            found = {piece: -math.log(1.0 - score) for piece, score in found.items()}
        return cls(found)

    def extend(self, word: str, best: list[tuple[float, int]], end: int) -> tuple[float, int]:
        """Forward score of the first ``end`` characters: (score, -pieces), from those of shorter prefixes."""
        scores = self.scores
        char = word[end - 1]
        top = None
        for start in range(max(0, end - self.longest), end):
            piece = scores.get(word[start:end])
            if piece is not None:
                score, used = best[start]
                here = (score + piece, used - 1)
                if top is None or here > top:
                    top = here
        if char not in scores:
            n = len(char.encode("utf-8", "surrogatepass"))
            score, used = best[end - 1]
            here = (score + n * self.byte_score, used - n)
            if top is None or here > top:
                top = here
        return top

    def count(self, word: str) -> int:
        """Tokens of one pre-token, computed alone."""
        best = [(0.0, 0)]
        for end in range(1, len(word) + 1):
            best.append(self.extend(word, best, end))
        return -best[-1][1]

    def count_sorted(self, words: list[str]) -> list[int]:
        """Tokens of sorted pre-tokens; a prefix shared with the word before is not computed again."""
        out, best, before = [], [(0.0, 0)], ""
        for word in words:
            shared, most = 0, min(len(word), len(before))
            while shared < most and word[shared] == before[shared]:
                shared += 1
            del best[shared + 1 :]
            for end in range(shared + 1, len(word) + 1):
                best.append(self.extend(word, best, end))
            out.append(-best[-1][1])
            before = word
        return out


_LOADED: dict[str, UnigramVocabulary] = {}


def _vocabulary(path: str) -> UnigramVocabulary:
    if path not in _LOADED:
        _LOADED[path] = UnigramVocabulary.load(path)
    return _LOADED[path]


def _counter(path: str, mark: str):
    def run(batches):
        vocabulary = _vocabulary(path)
        known = np.zeros(0, np.uint64)  # hashes of words met before, sorted, and their counts
        tokens = np.zeros(0, np.int64)
        for batch in batches:
            ids = batch.column(0)
            for first, off, starts, ends, doc, hashed, raw in cased_words(batch.column(1)):
                n_docs = len(off) - 1
                distinct, where, back = np.unique(hashed, return_index=True, return_inverse=True)
                slot = np.minimum(np.searchsorted(known, distinct), max(0, len(known) - 1))
                seen = known[slot] == distinct if len(known) else np.zeros(len(distinct), bool)
                value = np.zeros(len(distinct), np.int64)
                if len(known):
                    value[seen] = tokens[slot[seen]]
                new = np.flatnonzero(~seen)
                if len(new):
                    spelled = sorted((mark + raw[starts[w] : ends[w]].tobytes().decode("utf-8", "replace"), i) for i, w in zip(new.tolist(), where[new].tolist(), strict=True))
                    value[[i for _, i in spelled]] = vocabulary.count_sorted([s for s, _ in spelled])
                    if len(known) > MEMORY_WORDS:
                        known, tokens = known[:0], tokens[:0]
                    known = np.concatenate([known, distinct[new]])
                    tokens = np.concatenate([tokens, value[new]])
                    order = np.argsort(known)
                    known, tokens = known[order], tokens[order]
                per_doc = np.bincount(doc, minlength=n_docs)
                yield pa.RecordBatch.from_arrays(
                    [
                        ids.slice(first, n_docs).cast(pa.int64()),
                        pa.array(per_doc.astype(np.int64)),
                        pa.array(np.diff(off)),
                        pa.array(segment_sum(value[back], per_doc)),
                    ],
                    names=["doc_id", "n_words", "n_bytes", "n_tokens"],
                )

    return run


def cased_words(column):
    """Words with their case kept: (first row, offsets, starts, ends, document of each word, hash, bytes)."""
    table = word_bytes("space")
    for first, off, raw in chunks(column):
        start, end = split_spans(off, raw, table)
        power, inverse = powers(len(raw) + 1)
        total = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * power[: len(raw)], out=total[1:])
        yield first, off, start, end, np.searchsorted(off, start, "right") - 1, mix((total[end] - total[start]) * inverse[start], 1), raw


def count_tokens(docs: DataFrame, model: str | None = None, mark: str = WORD_MARK) -> DataFrame:
    """doc_id, n_words, n_bytes, n_tokens for every row of ``docs`` (doc_id, text)."""
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return own.mapInArrow(_counter(model or default_model(), mark), RESULT_SCHEMA)


def op3_token_counts(spark, sf_dir: str) -> DataFrame:
    return count_tokens(read_table(spark, sf_dir, "documents"))


QUERIES = {"op3_token_counts": op3_token_counts}

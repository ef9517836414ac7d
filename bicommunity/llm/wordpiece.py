"""Token counts by a linear longest-match automaton over a piece vocabulary."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkern import slices

VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
#: Marks the start of a word in the vocabulary.
WORD_START = "\u2581"
#: Words whose counts a task remembers.
REMEMBERED = 200_000


def load_pieces(path: str = VOCABULARY) -> list[str]:
    """Ordinary pieces of a sentencepiece file (no control, unknown or byte pieces)."""
    import sentencepiece

    p = sentencepiece.SentencePieceProcessor(model_file=path)
    return [p.id_to_piece(i) for i in range(p.get_piece_size()) if not (p.is_control(i) or p.is_unknown(i) or p.is_byte(i))]


class LongestMatch:
    """Counts the pieces of greedy longest-match splitting in one pass over a word.

    The trie's nodes are prefixes of pieces. ``count[v]`` is the number of pieces that
    greedy splitting takes off the front of v's string when no child goes on, and
    ``link[v]`` the node of what is left; both are worked out breadth first, so matching never goes back.
    Characters in no piece cost one piece for each UTF-8 byte.
    """

    def __init__(self, pieces: Iterable[str]):
        self.next: list[dict[str, int]] = [{}]
        self.link, self.count = [0], [0]
        final = [False]
        for piece in pieces:
            v = 0
            for c in piece:
                if c not in self.next[v]:
                    self.next[v][c] = len(self.next)
                    self.next.append({})
                    self.link.append(0)
                    self.count.append(0)
                    final.append(False)
                v = self.next[v][c]
            final[v] = v > 0
        todo = deque([(0, c, v) for c, v in self.next[0].items()])
        while todo:
            parent, c, v = todo.popleft()
            if final[v]:
                self.count[v] = 1
            elif not parent:
                self.count[v] = len(c.encode())
            else:
                at, popped = self.link[parent], self.count[parent]
                while at and c not in self.next[at]:
                    popped += self.count[at]
                    at = self.link[at]
                if c in self.next[at]:
                    self.link[v], self.count[v] = self.next[at][c], popped
                else:
                    self.count[v] = popped + len(c.encode())
            todo.extend((v, d, w) for d, w in self.next[v].items())

    def pieces(self, word: str) -> int:
        total, at = 0, 0
        nexts, link, count = self.next, self.link, self.count
        for c in word:
            while at and c not in nexts[at]:
                total += count[at]
                at = link[at]
            if c in nexts[at]:
                at = nexts[at][c]
            else:
                total += len(c.encode())
        while at:
            total += count[at]
            at = link[at]
        return total


def token_counts(docs: DataFrame, text: str = "text", vocabulary: str = VOCABULARY, pieces: list[str] | None = None) -> DataFrame:
    """``doc_id, n_words, n_tokens``: pieces of every word of the whole text.

    Each word is split with a start mark before it. The vocabulary (fixed size,
    read by the driver) goes to the executors with the kernel; a task builds the automaton once. A task
    remembers the counts of a bounded number of words. Null and blank texts have 0 of both; a row per input
    row; an empty table gives an empty result.
    """
    pieces = load_pieces(vocabulary) if pieces is None else pieces

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher, known = LongestMatch(pieces), {}
        for piece, texts in slices(batches, "text"):
            words, tokens = [], []
            for t in texts:
                own = t.split() if t else []
                total = 0
                for w in own:
                    n = known.get(w)
                    if n is None:
                        n = known[w] = matcher.pieces(WORD_START + w.decode())
                    total += n
                if len(known) > REMEMBERED:
                    known.clear()
                words.append(len(own))
                tokens.append(total)
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(words, pa.int64()), pa.array(tokens, pa.int64())], names=["doc_id", "n_words", "n_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, n_words long, n_tokens long")

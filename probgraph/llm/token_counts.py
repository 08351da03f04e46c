"""Operator 1: token counts by a unigram model, with forward scores shared in a trie.

The distinct pre-tokens (white-space words with a leading word mark) of a task are inserted in a trie. A node's
best forward score depends only on the path to it, so it is computed once for all words that share that prefix;
a word's token count is stored at its terminal. A document's count is the sum over its words. There is no
shuffle: each task owns its trie, and dropping a full trie changes no result.

Scores: the vocabulary file is a public one and is not trained on. It gives ranks; a piece of rank i gets
log(1 / ((i + 1) H)) by Zipf's law. A character that no piece has costs the lowest score less 10, and as many tokens as
UTF-8 bytes. Of segmentations with equal score the one with fewer tokens counts.

Null or empty text: 0 words, 0 tokens. Rows are kept one for one, repeated ones too."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
VOCAB = "/opt/tokenizers/piece_bpe_32k.model"
UNKNOWN_PENALTY = 10.0


def pieces(path: str) -> dict[str, float]:
    """Piece to score from a SentencePiece vocabulary file; control and byte pieces are left out."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    named = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
    total = math.log(sum(1 / (i + 1) for i in range(len(named))))
    return {p: -math.log(i + 1) - total for i, p in enumerate(named)}


class ForwardTrie:
    """Trie of pre-tokens whose nodes hold the best forward score and its token count."""

    def __init__(self, vocab: dict[str, float], max_nodes: int = 600_000):
        self.vocab, self.max_nodes = vocab, max_nodes
        self.longest = max(map(len, vocab))
        self.lowest = min(vocab.values()) - UNKNOWN_PENALTY
        # reversed pieces: which suffixes of a path are, or can grow to, a piece
        self.back: dict[str, float | None] = {}
        for p, s in vocab.items():
            for n in range(1, len(p)):
                self.back.setdefault(p[-n:], None)
            self.back[p] = s
        self.clear()

    def clear(self) -> None:
        self.next: list[dict[str, int]] = [{}]
        self.score, self.count = [0.0], [0]
        self.terminal: dict[str, int] = {}

    def tokens(self, word: str) -> int:
        """Tokens of a pre-token (its mark included)."""
        known = self.terminal.get(word)
        if known is not None:
            return known
        if len(self.score) > self.max_nodes or len(self.terminal) > self.max_nodes:
            self.clear()
        nxt, score, count, back = self.next, self.score, self.count, self.back
        node, path = 0, [0]
        for i, ch in enumerate(word):
            child = nxt[node].get(ch)
            if child is None:
                best, fewest = -math.inf, 0
                for j in range(i, max(-1, i - self.longest), -1):
                    piece = word[j : i + 1]
                    s = back.get(piece, 0)
                    if s == 0 and piece not in back:
                        break
                    if s is not None:
                        at = path[j]
                        v, c = score[at] + s, count[at] + 1
                        if v > best or v == best and c < fewest:
                            best, fewest = v, c
                if ch not in self.vocab:
                    v, c = score[node] + self.lowest, count[node] + len(ch.encode("utf-8", "surrogatepass"))
                    if v > best or v == best and c < fewest:
                        best, fewest = v, c
                child = len(score)
                nxt[node][ch] = child
                nxt.append({})
                score.append(best)
                count.append(fewest)
            node = child
            path.append(node)
        self.terminal[word] = count[node]
        return count[node]


def token_counts(docs: DataFrame, vocab_path: str = VOCAB, text: str = "text") -> DataFrame:
    """Columns of ``docs`` but the text, then ``n_words`` and ``n_tokens`` (existing columns of these names give way)."""
    keep = [c for c in docs.columns if c not in (text, "n_words", "n_tokens")]
    named = [f"c{i}" for i in range(len(keep))]
    inner = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(keep, named)], F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")).alias("body"))
    schema = ", ".join([f"{n} {inner.schema[n].dataType.simpleString()}" for n in named] + ["n_words bigint", "n_tokens bigint"])

    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = ForwardTrie(pieces(vocab_path))
        for b in batches:
            words, tokens = [], []
            for body in b.column(len(named)):
                bag = Counter((body.as_py() or "").split())
                words.append(sum(bag.values()))
                tokens.append(sum(n * trie.tokens(MARK + w) for w, n in bag.items()))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(words, pa.int64()), pa.array(tokens, pa.int64())], names=[*named, "n_words", "n_tokens"])

    return inner.mapInArrow(run, schema).select(*[F.col(n).alias(c) for n, c in zip(named, keep)], "n_words", "n_tokens")

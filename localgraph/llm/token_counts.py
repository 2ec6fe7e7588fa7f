"""Greedy longest-match token counts with a failure-link automaton.

The vocabulary is a byte trie. Every node that can no longer be extended has a failure link to the node
that represents what remains after the greedy pieces are cut off, and the number of those pieces; so one
pass over a word's bytes gives its number of greedy pieces in linear time, and no piece is built.

A word is a run of letters, of digits or of other visible characters, each with the one space before it,
or a run of white space; words cover the whole text. A word with a byte that no piece can start with
counts as one unknown token. The vocabulary is a parameter (a list of byte strings, at most MAX_PIECES);
it alone is sent to the executors. Counts of short words are remembered per worker in a table of at most
CACHE_WORDS entries, which changes no result.

Defined results: null or empty text -> 0 words, 0 tokens, 0 bytes. Every row is answered on its own, so
repeated and null ids keep their rows. Extra columns pass through; n_words, n_tokens, n_bytes are replaced.
"""

from __future__ import annotations

import json
import re
from collections import Counter

from pyspark.sql import DataFrame

from .common import table, tidied

MAX_PIECES = 1 << 20
CACHE_WORDS = 300_000
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.json"
_WORD = re.compile(r" ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+")
_BUILT: dict[int, Automaton] = {}


class Automaton:
    """Trie over bytes with failure links and counts of popped pieces."""

    def __init__(self, pieces: list[bytes]):
        self.goto: list[dict[int, int]] = [{}]
        self.depth = [0]
        whole = [False]
        for piece in pieces:
            at = 0
            for c in piece:
                nxt = self.goto[at].get(c)
                if nxt is None:
                    nxt = len(self.goto)
                    self.goto[at][c] = nxt
                    self.goto.append({})
                    whole.append(False)
                    self.depth.append(self.depth[at] + 1)
                at = nxt
            whole[at] = at > 0
        self.fail: list[int] = [-1] * len(self.goto)
        self.pops = [0] * len(self.goto)
        queue = [0]
        for node in queue:
            for c, child in self.goto[node].items():
                queue.append(child)
                if whole[child]:
                    self.fail[child], self.pops[child] = 0, 1
                    continue
                back, cut = self.fail[node], self.pops[node]
                while back >= 0 and c not in self.goto[back]:
                    cut += self.pops[back]
                    back = self.fail[back]
                if back >= 0:
                    self.fail[child], self.pops[child] = self.goto[back][c], cut

    def count(self, word: bytes) -> int:
        """Number of greedy longest-match pieces of word; 1 if it cannot be cut."""
        goto, fail, pops = self.goto, self.fail, self.pops
        at = n = 0
        for c in word:
            while (nxt := goto[at].get(c)) is None:
                n += pops[at]
                at = fail[at]
                if at < 0:
                    return 1
            at = nxt
        while at:
            n += pops[at]
            at = fail[at]
            if at < 0:
                return 1
        return n


def byte_vocabulary(path: str = VOCABULARY) -> list[bytes]:
    """Pieces of a byte-level vocabulary file as byte strings."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    of = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}
    with open(path, encoding="utf-8") as f:
        vocab = json.load(f)["model"]["vocab"]
    return [bytes(of[c] for c in piece) for piece in vocab if all(c in of for c in piece)]


def words_of(text: str) -> list[str]:
    return _WORD.findall(text)


def count_tokens(docs: DataFrame, pieces: list[bytes], text: str = "text") -> DataFrame:
    """docs with n_words, n_tokens, n_bytes appended."""
    if len(pieces) > MAX_PIECES:
        raise ValueError(f"more than {MAX_PIECES} pieces")
    shared, tag = docs.sparkSession.sparkContext.broadcast(pieces), hash(tuple(pieces))

    def counted(batches):
        auto = _BUILT.get(tag) or _BUILT.setdefault(tag, Automaton(shared.value))
        known: dict[str, int] = {}
        for batch in batches:
            found = []
            for value in batch[text]:
                words = Counter(words_of(value or ""))
                total = 0
                for word, times in words.items():
                    n = known.get(word)
                    if n is None:
                        n = auto.count(word.encode())
                        if len(word) <= 40:
                            if len(known) >= CACHE_WORDS:
                                known.clear()
                            known[word] = n
                    total += n * times
                found.append((words.total(), total, len((value or "").encode())))
            batch["n_words"], batch["n_tokens"], batch["n_bytes"] = ([f[i] for f in found] for i in range(3))
            yield batch

    docs = docs.drop("n_words", "n_tokens", "n_bytes")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInPandas(tidied(counted), f"{fields}, n_words bigint, n_tokens bigint, n_bytes bigint")


def op2_token_counts(spark, sf_dir: str, vocabulary: str = VOCABULARY) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return count_tokens(docs, byte_vocabulary(vocabulary)).drop("text")

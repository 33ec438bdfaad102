"""Word-piece counts by a longest-match automaton that never goes back and never builds a piece.

The vocabulary's tries (pieces that begin a word, pieces that continue one) get failure links as in linear longest-match
tokenisation: where a character does not fit, the link leads to the node for what is left once the longest pieces have been taken
off the front, and how many were taken off is stored with the link. Each character is looked at once and moves the sum on.
A word with no tokenisation is one unknown token, as word-piece has it.

Words are runs of characters other than space and \\x09-\\x0D. Each worker keeps the counts of words it has seen in a bounded table.

Defined cases: null and empty texts have no words. Repeated rows, null ids and extra columns change nothing.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_text, raw_texts, worker_state
from .packing import CHUNK_BYTES, KNOWN_CHUNKS, Kept

NONE = -1


class Automaton:
    """Nodes are numbers; node 0 begins a word, node 1 goes on within it."""

    def __init__(self, begin: set[str], go_on: set[str]):
        self.next: list[dict[str, int]] = [{}, {}]
        ends = [False, False]
        for root, pieces in ((0, begin), (1, go_on)):
            for p in pieces:
                at = root
                for c in p:
                    nxt = self.next[at].get(c)
                    if nxt is None:
                        nxt = self.next[at][c] = len(self.next)
                        self.next.append({})
                        ends.append(False)
                    at = nxt
                ends[at] = ends[at] or bool(p)
        self.link = [NONE] * len(self.next)
        self.popped = [0] * len(self.next)
        level = [0, 1]
        while level:
            after = []
            for v in level:
                for c, u in self.next[v].items():
                    if ends[u]:
                        self.link[u], self.popped[u] = 1, 1
                    else:
                        z, n = self.link[v], self.popped[v]
                        while z != NONE and c not in self.next[z]:
                            n += self.popped[z]
                            z = self.link[z]
                        if z != NONE:
                            self.link[u], self.popped[u] = self.next[z][c], n
                    after.append(u)
            level = after

    def count(self, word: str) -> int:
        """Number of pieces of a non-empty word; 0 if it has none."""
        at, n = 0, 0
        steps, link, popped = self.next, self.link, self.popped
        for c in word:
            while (nxt := steps[at].get(c)) is None:
                n += popped[at]
                at = link[at]
                if at == NONE:
                    return 0
            at = nxt
        while at != 1:
            n += popped[at]
            at = link[at]
            if at == NONE:
                return 0
        return n


def vocabulary(path: str) -> tuple[set[str], set[str]]:
    """(pieces that begin a word, pieces that continue one) of a SentencePiece model file."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    begin, go_on = set(), set()
    for i in range(sp.get_piece_size()):
        if sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i):
            continue
        p = sp.id_to_piece(i)
        (begin if p.startswith("▁") else go_on).add(p.removeprefix("▁"))
    return begin - {""}, go_on - {""}


def count_tokens(docs: DataFrame, path: str, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns, n_words, n_tokens (unknown words count one each) and n_unknown, bigint."""
    outputs = ("n_words", "n_tokens", "n_unknown")
    carry = tuple(c for c in carry if c not in outputs)
    types = dict(docs.dtypes)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        auto, known = worker_state(("automaton", path), lambda: (Automaton(*vocabulary(path)), Kept(KNOWN_CHUNKS)))
        cols: tuple[list, list, list] = ([], [], [])
        for t in raw_texts(b.column("text")):
            words = t.split()
            got = list(map(known.young.get, words))
            if None in got:
                for i, x in enumerate(got):
                    if x is None:
                        x = known.get(words[i])
                        if x is None:
                            x = auto.count(words[i].decode())
                            if len(words[i]) <= CHUNK_BYTES:
                                known.put(words[i], x)
                        got[i] = x
            unknown = got.count(0)
            for c, v in zip(cols, (len(words), sum(got) + unknown, unknown), strict=True):
                c.append(v)
        return pa.RecordBatch.from_arrays([*(b.column(c) for c in carry), *(pa.array(x, pa.int64()) for x in cols)], [*carry, *outputs])

    return map_text(docs.select(*dict.fromkeys([*carry, "text"])), run, ", ".join([*(f"`{c}` {types[c]}" for c in carry), "n_words bigint, n_tokens bigint, n_unknown bigint"]))

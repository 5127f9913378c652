"""Operator 3: token counts with a whole-token shortcut.

A sentencepiece BPE model with an identity normaliser never merges across the start of a run of
blanks: no piece has the blank sign after another sign (proved for the model at hand when the tables
are made; a model that fails the proof is counted text by text). A text is thus a series of
pre-tokens - a run of blanks with the word after it - that are encoded each on its own.

Offline, every vocabulary string that is a possible pre-token is encoded alone; those that give one
token make the shortcut table. Counting then is a lookup for most pre-tokens; the rest are merged by
the library once per distinct string, kept in a memo of bounded size.

A ``tokenizers`` model has no such proof for all its parts (normalisers, special strings) and is
counted by the library itself.

Defined cases: null as empty text, 0 tokens; texts are counted whole; repeated rows are counted alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.llm.textarrays import chunks

LIMIT, MEMO = 4096, 1 << 19
MARK = "▁"


class PieceCounter:
    """Counts of the tokens of texts by a sentencepiece model."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = m = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = [m.id_to_piece(i) for i in range(m.get_piece_size()) if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i) or m.is_unused(i))]
        probes = ("a  b", " a ", "\ta\nb", "ﬁ①Å é", "")
        plain = all(m.decode(m.encode(x)) == x for x in probes)
        self.separable = plain and not any(MARK in p.lstrip(MARK) for p in pieces)
        self.single: dict[str, int] = {}
        if self.separable:
            begins = [p for p in pieces if p.startswith(MARK) and p.count(MARK) == 1]
            self.single = {MARK: len(m.encode("a ")) - len(m.encode("a"))}  # one blank at the end of a text
            self.single |= {p[1:]: 1 for p, got in zip(begins, m.encode([p[1:] for p in begins], num_threads=1)) if len(got) == 1}
        self.memo: dict[str, int] = dict(self.single)

    def count(self, text: str) -> int:
        if not text:
            return 0
        if not self.separable or MARK in text:
            return len(self.model.encode(text, num_threads=1))
        parts = text.split(" ")
        if "" in parts:  # runs of blanks, or blanks at an end
            parts = self._runs(parts)
        counts = list(map(self.memo.get, parts))
        if None in counts:
            self._learn([p for p, c in zip(parts, counts) if c is None])
            counts = [self.memo[p] if c is None else c for p, c in zip(parts, counts)]
        return sum(counts)

    def _runs(self, parts: list[str]) -> list[str]:
        """Empty parts join the part that follows them: k blanks and a word are one pre-token."""
        out, blanks = [], 0
        for p in parts:
            if p:
                out.append(" " * blanks + p)
                blanks = 0
            else:
                blanks += 1
        if blanks:
            out.append(" " * (blanks - 1) if blanks > 1 else MARK)
        return out

    def _learn(self, parts: list[str]) -> None:
        """Encode each once. The model puts one blank before a text, so a pre-token goes in without its first blank."""
        new = list(dict.fromkeys(parts))
        if len(self.memo) + len(new) > MEMO + len(self.single):
            self.memo = dict(self.single)  # begun anew; the caller has the counts it found
        for p, got in zip(new, self.model.encode(new, num_threads=1)):
            self.memo[p] = len(got)


class LibraryCounter:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.no_truncation()
        self.model.no_padding()

    def count(self, text: str) -> int:
        return len(self.model.encode(text, add_special_tokens=False).ids)


_counters: dict[str, object] = {}


def counter(path: str):
    """One per process and file."""
    if path not in _counters:
        _counters[path] = LibraryCounter(path) if path.endswith(".json") else PieceCounter(path)
    return _counters[path]


def counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every row of ``docs``."""
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    kind = dict(rows.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(path)
        for b in batches:
            n, t = [], []
            for part in chunks(b.column(1)):
                for i in range(part.n):
                    raw = part.text(i)
                    n.append(len(raw))
                    t.append(c.count(raw.decode("utf-8", "replace")))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(t, pa.int64()), pa.array([x > limit for x in t], pa.bool_())], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return rows.mapInArrow(run, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean")

"""Token counts (1): byte-pair merging with a heap and a linked list.

A text is cut into units that no merge can cross; the count of a unit is its
initial symbols minus the merges done, plus the extra bytes of symbols that the
vocabulary lacks (byte fallback).  Units repeat, so each worker keeps the counts
of recent ones in a table of bounded size.

Null and empty texts have 0 tokens.  Very long texts are worked on whole, unit
by unit.  Rows that repeat give repeated rows; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"

#: Units whose counts a worker keeps; beyond it the table starts anew.
UNITS_KEPT = 400_000


class Merger:
    """Counts tokens with the pieces of a sentencepiece BPE model.

    The model's own settings are checked: identity normalisation, a space put
    in front, no white space removed, byte fallback, no piece with a space
    after another character.
    """

    def __init__(self, model_path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        usable = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        #: A lower rank merges first.
        self.rank = {model.id_to_piece(i): -model.get_score(i) for i in usable}
        if any(SPACE in p.lstrip(SPACE) for p in self.rank):
            raise ValueError("pieces may cross spaces; the units would be wrong")
        if model.encode("  a  ", out_type=str) != self.plain("  a  "):
            raise ValueError("the model normalises texts in a way that is not covered")
        self.known_chars = {p for p in self.rank if len(p) == 1}
        self.fences = [c for c in "\n" if not any(c in p for p in self.rank)]
        self.opened = _Counts(self, SPACE)
        self.bare = _Counts(self, "")
        self.run = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")

    def merged(self, unit: str) -> list[str]:
        """The symbols of a unit after all merges."""
        rank, text = self.rank, list(unit)
        n = len(text)
        before, after = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = []
        for i in range(n - 1):
            r = rank.get(text[i] + text[i + 1])
            if r is not None:
                heap.append((r, i, text[i] + text[i + 1]))
        heapq.heapify(heap)
        while heap:
            _, i, both = heapq.heappop(heap)
            j = after[i]
            # Stale entries: one of the two symbols has since changed or gone.
            if text[i] is None or j >= n or text[j] is None or text[i] + text[j] != both:
                continue
            text[i], text[j] = both, None
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                r = rank.get(both + text[k])
                if r is not None:
                    heapq.heappush(heap, (r, i, both + text[k]))
            h = before[i]
            if h >= 0:
                r = rank.get(text[h] + both)
                if r is not None:
                    heapq.heappush(heap, (r, h, text[h] + both))
        return [x for x in text if x is not None]

    def unit_count(self, unit: str) -> int:
        count = 0
        for piece in self.merged(unit):
            count += 1 if piece in self.rank else len(piece.encode("utf-8", "surrogatepass"))
        return count

    def plain(self, text: str) -> list[str]:
        """Pieces of a whole text (used for checks and tests)."""
        out = []
        for piece in self.merged(SPACE + text.replace(" ", SPACE)) if text else []:
            out += [piece] if piece in self.rank else [f"<0x{b:02X}>" for b in piece.encode("utf-8")]
        return out

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if len(self.opened) + len(self.bare) > UNITS_KEPT:
            self.opened.clear()
            self.bare.clear()
        lines = text.split("\n") if self.fences else [text]
        total, table = len(lines) - 1, self.opened
        for line in lines:
            if SPACE in line or "  " in line or line[:1] == " " or line[-1:] == " ":
                total += self.awkward(line, table is self.opened)
            else:
                words = line.split(" ")
                if words[0]:
                    total += table[words[0]]
                elif table is self.opened:
                    total += self.unit_count(SPACE)
                total += sum(map(self.opened.__getitem__, words[1:]))
            table = self.bare
        return total

    def awkward(self, line: str, opens: bool) -> int:
        """A line with runs of spaces, or with the space mark itself."""
        line = (SPACE if opens else "") + line.replace(" ", SPACE)
        return sum(self.bare[unit] for unit in self.run.findall(line))


class _Counts(dict):
    def __init__(self, merger: Merger, prefix: str):
        super().__init__()
        self.merger, self.prefix = merger, prefix

    def __missing__(self, word: str) -> int:
        self[word] = n = self.merger.unit_count(self.prefix + word)
        return n


@lru_cache(maxsize=2)
def merger(model_path: str) -> Merger:
    return Merger(model_path)


#: Texts up to so many bytes go through the library itself, some of them at a time.
LIBRARY_BYTES = 1 << 20


def token_lengths(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id and n (tokens) of each row, for operators that need lengths only.

    The library counts, which is faster than merging here; longer texts, for which
    it would need memory in proportion, are merged unit by unit as in ``token_counts``.
    The numbers are the same.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import sentencepiece

        library = sentencepiece.SentencePieceProcessor(model_file=model_path)
        for batch in batches:
            text, n = pc.fill_null(batch.column(1), ""), []
            sizes = pc.binary_length(text).to_numpy(zero_copy_only=False)
            row = 0
            while row < len(text):
                end, held = row, 0
                while end < len(text) and (end == row or held + sizes[end] <= LIBRARY_BYTES):
                    held += sizes[end]
                    end += 1
                if held > LIBRARY_BYTES:
                    n.append(merger(model_path).count(text[row].as_py()))
                else:
                    n += [len(x) for x in library.encode(text.slice(row, end - row).to_pylist(), num_threads=1)]
                row = end
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64())], ["doc_id", "n"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(count, "doc_id long, n long")


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit (n_tokens > limit) of each row."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = merger(model_path)
        for batch in batches:
            text = pc.fill_null(batch.column(1), "")
            tokens = pa.array([m.count(x.as_py()) for x in text], pa.int64())
            n_bytes = pc.binary_length(text).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), n_bytes, tokens, pc.greater(tokens, limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select("doc_id", "text").mapInArrow(count, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_bytes long, n_tokens long, over_limit boolean")

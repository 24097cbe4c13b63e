"""Token counts from per-document pre-token frequencies, without building ids.

A text is cut before each space that stands between two non-white characters, and a run of letters is cut
from the marks after it. Byte-level BPE never merges over such a cut, so the piece count of a text is the sum,
over its distinct pre-tokens, of frequency times piece count. Slices of texts are reduced to their distinct
pre-tokens; each worker counts the pieces of one once, in a dictionary of bounded size that lives as long as the
worker, and joins it to the frequencies of each document. No rows are shuffled: a global dictionary of
pre-tokens would have to be shuffled against a posting for nearly every word of the corpus, which is more than
the corpus itself.
"""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import Generations, as_list, byte_level, distinct_words, map_slices, texts_of

SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"


#: Marks that end a word and are a pre-token of their own there (no apostrophe: contractions are not).
TAIL = ",.;:!?*&%#$"
_LETTERS = "[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+"


class PretokenCounter:
    """Piece counts of texts under one byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str, entries: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        #: Pieces of " " + pre-token, and of a text's first word; -1 where white space at an edge makes the cut unsafe.
        self.led = Generations(lambda w: self._safe([w], " ")[0], entries, lambda ws: self._safe(ws, " "))
        self.opening = Generations(lambda w: self._safe([w], "")[0], entries // 4, lambda ws: self._safe(ws, ""))
        self.marks = Generations(lambda w: self._pieces([w])[0] if w else 0, entries // 4)
        # letters and the marks after them are pre-tokens of their own if nothing rewrites the text before
        added = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.plain = self.tok.normalizer is None and str(self.tok.pre_tokenizer).startswith("ByteLevel(") and not any(re.fullmatch(f"(?:{_LETTERS[:-1]}|[{TAIL}])+", t) for t in added)

    def _pieces(self, texts: list[str]) -> list[int]:
        return [len(e) for e in self.tok.encode_batch(texts, add_special_tokens=False)]

    def _safe(self, words: list[str], lead: str) -> list[int]:
        tokenize, out, rest = self.tok.model.tokenize, [], []
        for i, w in enumerate(words):
            if not w or w[0].isspace() or w[-1].isspace():
                out.append(-1)
            elif self.plain and w.isalpha() and max(w) < "\u0100":
                out.append(len(tokenize(byte_level(lead + w))))
            else:
                out.append(0)
                rest.append(i)
        for i, n in zip(rest, self._pieces([lead + words[i] for i in rest]) if rest else ()):
            out[i] = n
        return out

    def counts(self, texts: pa.Array) -> np.ndarray:
        if not len(texts):
            return np.zeros(0, np.int64)
        bounds, codes, words = distinct_words(texts)
        run, tail = words, pa.nulls(len(words), pa.string()).fill_null("")
        if self.plain:
            letters = pc.utf8_rtrim(words, TAIL)
            cut = pc.match_substring_regex(letters, f"^{_LETTERS}$")
            run, tail = pc.if_else(cut, letters, words), pc.if_else(cut, pc.replace_substring_regex(words, f"^{_LETTERS}", "", max_replacements=1), "")
        run, tail = run.dictionary_encode(), tail.dictionary_encode()
        led = np.array(self.led.all(as_list(run.dictionary)), np.int64)[run.indices.to_numpy()]
        marks = np.array(self.marks.all(as_list(tail.dictionary)), np.int64)[tail.indices.to_numpy()]
        # frequencies times counts, as sums over the words of each text; its first word has no space before it
        each = np.concatenate([[0], np.cumsum((led + marks)[codes])])
        unsafe = np.concatenate([[0], np.cumsum(led[codes] < 0)])
        heads = codes[bounds[:-1]]
        first = np.array(self.opening.all(words.take(pa.array(heads)).to_pylist()), np.int64)
        out = each[bounds[1:]] - each[bounds[:-1] + 1] + first
        whole = np.flatnonzero((first < 0) | (unsafe[bounds[1:]] > unsafe[bounds[:-1] + 1]))
        for i in whole.tolist():
            text = texts[i].as_py()
            out[i] = self._pieces([text])[0] if text else 0
        return out


_COUNTERS: dict[tuple[str, int], PretokenCounter] = {}


def _counter(path: str, entries: int) -> PretokenCounter:
    if (path, entries) not in _COUNTERS:
        _COUNTERS[path, entries] = PretokenCounter(path, entries)
    return _COUNTERS[path, entries]


def count_tokens(docs: DataFrame, tokenizer: str, limit: int = 512, entries: int = 600_000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Tokens of every whole text: ``doc_id, n_bytes, n_tokens, over_limit``.

    Null texts count as empty (0 bytes, 0 tokens); repeated rows and null keys pass through, an empty
    table gives no rows, other columns are not read. ``entries`` bounds a worker's dictionary; it
    never changes a count.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        n = _counter(tokenizer, entries).counts(batch["text"])
        size = pc.cast(pc.binary_length(batch["text"]), pa.int64())
        return pa.RecordBatch.from_arrays([batch["doc_id"], size, pa.array(n), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return map_slices(texts_of(docs, key, text), run, SCHEMA, rows=1000)

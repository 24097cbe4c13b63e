"""Merge-type piece encoding by backtracking, and decoding.

A text, with spaces as the visible space mark, is cut before each run of marks: no piece of the model
has a mark after another character, so the encoding of a text joins those of its segments. A segment
is encoded left to right: the longest piece at a position (one Aho-Corasick pass), then its next
shorter prefixes; a piece is taken if merging it anew with its left neighbour gives the same two
pieces back, and a bitfield holds positions from which no encoding leads on. Segments with runs of
marks hold pieces of equal score, where only the order of merges decides; they are merged directly.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from array import array

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import Generations, as_list, distinct_words, gather, map_slices, texts_of

MARK = "▁"
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
IDS_SCHEMA = "doc_id long, ids array<int>"


class PieceEncoder:
    """Encoder for one sentencepiece BPE model with an identity normaliser and byte fallback."""

    def __init__(self, path: str, entries: int = 400_000):
        import sentencepiece

        self.sp = sp = sentencepiece.SentencePieceProcessor(model_file=path)
        self.entries = entries
        n = sp.get_piece_size()
        self.bytes_ = {}
        self.ids: dict[str, int] = {}
        for i in range(n):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.bytes_[int(piece[3:5], 16)] = i
            elif not (sp.is_control(i) or sp.is_unknown(i)):
                self.ids[piece] = i
        self.score = {p: sp.get_score(i) for p, i in self.ids.items()}
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("a piece holds a space mark after other characters; texts can't be cut there")
        self.reach = {p for p in self.ids if len(p) == 1 or MARK * 2 in p or self.merge(p) == [p]}
        self.shorter = {p: next((p[:k] for k in range(len(p) - 1, 1, -1) if p[:k] in self.reach), p[0] if len(p) > 1 else "") for p in self.reach}
        self.found = ahocorasick.Automaton()
        for p in self.reach:
            self.found.add_word(p[::-1], p)
        self.found.make_automaton()
        self.fits: dict[tuple[str, str], bool] = {}
        #: Ids of words with the mark before them.
        self.known = Generations(lambda w: self._pack(self.segment(MARK + w)), entries)
        self.runs = re.compile(f"{MARK}+[^{MARK}]*")

    def merge(self, s: str) -> list[str]:
        """The plain procedure: best score first, leftmost among equals."""
        part, nxt, prv = list(s), list(range(1, len(s) + 1)), list(range(-1, len(s) - 1))
        score, heap, end = self.score, [], len(s)
        for i in range(end - 1):
            v = score.get(s[i : i + 2])
            if v is not None:
                heap.append((-v, i, 2))
        heapq.heapify(heap)
        while heap:
            _, i, size = heapq.heappop(heap)
            j = nxt[i] if part[i] else end
            if j >= end or not part[i] or len(part[i]) + len(part[j]) != size:
                continue
            part[i] += part[j]
            part[j] = ""
            nxt[i] = nxt[j]
            if nxt[i] < end:
                prv[nxt[i]] = i
                v = score.get(part[i] + part[nxt[i]])
                if v is not None:
                    heapq.heappush(heap, (-v, i, size + len(part[nxt[i]])))
            if prv[i] >= 0:
                k = prv[i]
                v = score.get(part[k] + part[i])
                if v is not None:
                    heapq.heappush(heap, (-v, k, size + len(part[k])))
        return [p for p in part if p]

    def _fit(self, a: str, b: str) -> bool:
        if len(self.fits) > self.entries:
            self.fits.clear()
        ok = self.fits[a, b] = self.merge(a + b) == [a, b]
        return ok

    def segment(self, s: str) -> list[str]:
        """Pieces of a segment with one leading mark at most."""
        n = len(s)
        longest = list(s)
        for end, p in self.found.iter(s[::-1]):
            at = n - 1 - end
            if len(p) > len(longest[at]):
                longest[at] = p
        out: list[str] = []
        at, alive, fits, shorter = 0, bytearray(b"\x01") * (n + 1), self.fits, self.shorter
        p = longest[0] if n else ""
        while at < n:
            left = out[-1] if out else ""
            while p:
                if alive[at + len(p)] and (not left or (fits[left, p] if (left, p) in fits else self._fit(left, p))):
                    break
                p = shorter.get(p, "")
            if p:
                out.append(p)
                at += len(p)
                p = longest[at] if at < n else ""
            else:
                alive[at] = 0
                if not out:
                    return self.merge(s)
                p = out.pop()
                at -= len(p)
                p = shorter.get(p, "")
        return out

    def _pack(self, pieces: list[str]) -> bytes:
        ids = []
        for p in pieces:
            i = self.ids.get(p)
            if i is None:
                ids.extend(self.bytes_[b] for b in p.encode())
            else:
                ids.append(i)
        return array("I", ids).tobytes()

    def encode(self, text: str) -> bytes:
        """Ids of one text as little-endian 32-bit integers, without begin and end."""
        if not text:
            return b""
        out = []
        for s in self.runs.findall(MARK + text.replace(" ", MARK)):
            if s[1:2] == MARK or s == MARK:
                out.append(self._pack(self.merge(s)))
            else:
                out.append(self.known[s[1:]])
        return b"".join(out)

    def encode_all(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text with begin and end; distinct words of the slice are encoded once."""
        if not len(texts):
            return []
        bounds, codes, words = distinct_words(pc.replace_substring(texts, MARK, " "))
        names = as_list(words)
        ids, ends = gather(self.known.all(names), codes, "<u4")
        # an empty word is a run of marks, or a text's edge: there the order of merges decides
        empty = np.concatenate([[0], np.cumsum(codes == names.index(""))]) if "" in names else None
        bos, eos = [np.array([i], "<u4") for i in (self.sp.bos_id(), self.sp.eos_id())]
        out = []
        for i, (lo, hi) in enumerate(zip(bounds.tolist(), bounds[1:].tolist())):
            own = ids[ends[lo] : ends[hi]]
            if empty is not None and empty[hi] > empty[lo]:
                own = np.frombuffer(self.encode(texts[i].as_py()), "<u4")
            out.append(np.concatenate([bos, own, eos]))
        return out

    def ids_of(self, text: str) -> np.ndarray:
        """Ids of one text with begin and end."""
        return self.encode_all(pa.array([text], pa.string()))[0]


_ENCODERS: dict[tuple[str, int], PieceEncoder] = {}


def encoder(path: str, entries: int = 400_000) -> PieceEncoder:
    if (path, entries) not in _ENCODERS:
        _ENCODERS[path, entries] = PieceEncoder(path, entries)
    return _ENCODERS[path, entries]


def encode(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, ids`` of every whole text, with begin and end ids; a null text counts as empty."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        got = [ids.tolist() for ids in encoder(model).encode_all(batch["text"])]
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(got, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return map_slices(texts_of(docs, key, text), run, IDS_SCHEMA)


def decode(coded: DataFrame, model: str) -> DataFrame:
    """``doc_id, text`` from ``doc_id, ids``; null ids count as none."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        got = [encoder(model).sp.decode(x or []) for x in batch["ids"].to_pylist()]
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(got, pa.string())], names=["doc_id", "text"])

    return map_slices(coded.select("doc_id", "ids"), run, "doc_id long, text string")


def round_trip_digests(docs: DataFrame, model: str, entries: int = 400_000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Encode and decode every whole text in one pass: ``doc_id, n_tokens, ids_sha256, decoded_sha256``.

    Null texts count as empty (begin and end ids alone); repeated rows and null keys pass through; an
    empty table gives no rows; other columns are not read.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        enc = encoder(model, entries)
        n, a, b = [], [], []
        for ids in enc.encode_all(batch["text"]):
            n.append(len(ids))
            a.append(hashlib.sha256(ids.tobytes()).hexdigest())
            b.append(hashlib.sha256(enc.sp.decode(ids.tolist()).encode()).hexdigest())
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return map_slices(texts_of(docs, key, text), run, SCHEMA, rows=1000)

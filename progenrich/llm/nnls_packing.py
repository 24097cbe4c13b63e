"""Packing of tokenised documents into windows by non-negative least squares on the length histogram.

1. Each text becomes ids; a document longer than the window is cut into full windows and a rest. Only
   lengths, offsets and checksums of the pieces are kept.
2. Lengths are counted; the histogram has as many entries as the window has tokens, whatever the input.
3. On the driver, from the histogram alone: shallow combinations of coarse lengths which fill the window
   are enumerated, non-negative least squares gives their repeat counts, these are rounded down, and what
   is left is packed greedily, longest first, into the tightest space that fits.
4. Pieces of one length are numbered (in salted runs, so that no length lands in one task) and look up the
   place that the plan has for their number.
"""

from __future__ import annotations

import bisect
import os
import zlib
from array import array
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Generations, Workspace, as_list, byte_level, distinct_words, gather, map_slices, salts, texts_of

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"
PLACED = PIECES + ", sequence_id long, offset long"


#: Marks that may end a word and are pre-tokens of their own there (no apostrophe: contractions are not).
TAIL = ",.;:!?*&%#$"
#: Letters of the first 256 code points: their bytes need no normaliser but lower case.
_LETTERS = "[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+"


class WordIds:
    """Ids of texts under a word-level BPE file that drops white space and lower-cases.

    White space parts pre-tokens, so a text's ids join those of its space-cut words; a run of letters and the
    marks after it are pre-tokens too. Texts go by slices: each distinct run of a slice is looked up once in a
    dictionary of bounded size, and its ids are laid out wherever it stands.
    """

    def __init__(self, path: str, entries: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        #: Ids are kept in two bytes each where the vocabulary allows.
        self.kind = "H" if self.tok.get_vocab_size() <= 1 << 16 else "I"
        self.runs = Generations(lambda r: self._runs([r])[0], entries, self._runs)

    def _runs(self, runs: list[str]) -> list[bytes]:
        """Ids of runs. The model alone sees lower-case letters of the first 256 code points."""
        tokenize, kind, out = self.tok.model.tokenize, self.kind, []
        for r in runs:
            plain = r.isalpha() and r.islower() and (r.isascii() or max(r) < "\u0100")
            out.append(array(kind, [t.id for t in tokenize(r if r.isascii() else byte_level(r))]).tobytes() if plain else None)
        rest = [i for i, x in enumerate(out) if x is None]
        for i, e in zip(rest, self.tok.encode_batch([runs[i] for i in rest], add_special_tokens=False) if rest else ()):
            out[i] = array(kind, e.ids).tobytes()
        return out

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after the other, and the bounds by text."""
        bounds, codes, words = distinct_words(pc.replace_substring(texts, "\n", " "))
        letters = pc.utf8_rtrim(words, TAIL)
        plain = pc.match_substring_regex(letters, f"^{_LETTERS}$")
        run = pc.if_else(plain, pc.utf8_lower(letters), words)
        tail = pc.if_else(plain, pc.replace_substring_regex(words, f"^{_LETTERS}", "", max_replacements=1), "")
        units = pa.concat_arrays([run, tail]).dictionary_encode()
        unit = units.indices.to_numpy().reshape(2, -1)
        ids, ends = gather(self.runs.all(as_list(units.dictionary)), unit[:, codes].T.reshape(-1), f"<u{array(self.kind).itemsize}")
        return ids, ends[2 * bounds]


_WORDS: dict[tuple[str, int], WordIds] = {}


def _word_ids(path: str, entries: int) -> WordIds:
    if (path, entries) not in _WORDS:
        _WORDS[path, entries] = WordIds(path, entries)
    return _WORDS[path, entries]


def cut_documents(docs: DataFrame, tokenizer: str, window: int, end_id: int, entries: int = 400_000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces of at most ``window`` ids; the last id of each document is ``end_id``. Null texts count as empty."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids, bounds = _word_ids(tokenizer, entries).encode(batch["text"])
        raw = memoryview(np.insert(ids.astype("<u4"), bounds[1:], end_id).tobytes())
        bounds = (bounds + np.arange(len(bounds))).tolist()
        rows = []
        for doc, lo, hi in zip(batch["doc_id"].to_pylist(), bounds, bounds[1:]):
            for at in range(lo, hi, window):
                to = min(at + window, hi)
                rows.append((doc, at - lo, to - at, zlib.crc32(raw[4 * at : 4 * to]), hi - lo))
        cols = list(zip(*rows)) or [()] * 5
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return map_slices(texts_of(docs, key, text), run, PIECES, rows=1000)


def nnls(a: np.ndarray, b: np.ndarray, rounds: int = 400) -> np.ndarray:
    """Active-set non-negative least squares: columns enter by their gradient, negative ones leave."""
    n = a.shape[1]
    x, active = np.zeros(n), np.zeros(n, bool)
    for _ in range(rounds):
        slope = a.T @ (b - a @ x)
        slope[active] = -np.inf
        j = int(np.argmax(slope))
        if slope[j] <= 1e-9 * max(1.0, float(np.abs(b).max())):
            break
        active[j] = True
        while True:
            cols = np.flatnonzero(active)
            z = np.zeros(n)
            z[cols] = np.linalg.lstsq(a[:, cols], b, rcond=None)[0]
            low = cols[z[cols] <= 0]
            if not len(low):
                x = z
                break
            step = np.min(x[low] / np.maximum(x[low] - z[low], 1e-300))
            x = x + step * (z - x)
            gone = cols[x[cols] <= 1e-12]
            gone = gone if len(gone) else low
            x[gone] = 0
            active[gone] = False
            if not active.any():
                break
    return x


def combinations(total: int, least: int, depth: int = 3) -> list[tuple[tuple[int, int], ...]]:
    """Shallow ways to fill ``total`` with coarse lengths of ``least`` or more: tuples of (length, repeats), longest first.

    Either at most ``depth`` long lengths (a quarter of the window or more), or two different lengths of any
    size, each repeated: a way has few different lengths however many pieces it holds.
    """
    out: set[tuple[tuple[int, int], ...]] = set()
    for a in range(least, total + 1):
        for m in range(1, total // a + 1):
            rest = total - m * a
            if not rest:
                out.add(((a, m),))
            for b in range(least, min(a - 1, rest) + 1):
                if rest % b == 0:
                    out.add(((a, m), (b, rest // b)))

    def grow(part: tuple[int, ...], rest: int, most: int) -> None:
        if rest == 0:
            out.add(tuple((k, part.count(k)) for k in sorted(set(part), reverse=True)))
        elif len(part) < depth:
            for k in range(min(most, rest), max(least, total // 8) - 1, -1):
                if (depth - len(part)) * k < rest:
                    break
                grow((*part, k), rest - k, k)

    grow((), total, total)
    return sorted(out)


@dataclass
class Plan:
    """Sequences in groups: ``groups`` holds (how many alike, lengths in order)."""

    window: int
    groups: list[tuple[int, tuple[int, ...]]]

    @property
    def sequences(self) -> int:
        return sum(n for n, _ in self.groups)

    def layout(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Sorted keys (length, first number), first number, first sequence, offset."""
        used: dict[int, int] = {}
        rows, base = [], 0
        for n, lengths in self.groups:
            at = 0
            for size in lengths:
                lo = used.get(size, 0)
                rows.append(((size << 40) + lo, lo, base, at))
                used[size] = lo + n
                at += size
            base += n
        rows.sort()
        cols = np.array(rows, np.int64).reshape(-1, 4)
        return cols[:, 0], cols[:, 1], cols[:, 2], cols[:, 3]


def solve(left: np.ndarray, window: int, grid: int = 16, least: int = 8, share: float = 0.9) -> dict[int, list[tuple[int, tuple[int, ...]]]]:
    """Sequences by least squares: free space -> (how many alike, lengths). What they hold is taken off ``left``.

    Repeat counts of shallow combinations are solved against the histogram of coarse lengths (``grid`` tokens a step;
    lengths under ``least`` steps are left to fill gaps). ``share`` of the counts is taken, rounded down.
    """
    if window % grid or window // grid < 4:
        grid = 1
    steps = window // grid
    least = min(least, max(1, steps // 8))
    coarse = -(-np.arange(window + 1) // grid)
    free: dict[int, list[tuple[int, tuple[int, ...]]]] = {}
    ways = combinations(steps, least) if left.sum() and steps <= 256 else []
    if ways:
        a = np.zeros((steps + 1, len(ways)))
        for j, way in enumerate(ways):
            for k, m in way:
                a[k, j] = m
        have = np.bincount(np.minimum(coarse, steps), weights=left, minlength=steps + 1)
        have[:least] = 0
        repeats = nnls(a, have) * share
        lists = {k: [[n, int(left[n])] for n in range(min(window, k * grid), (k - 1) * grid, -1) if left[n]] for k in range(least, steps + 1)}
        stock = have.astype(np.int64)
        for j in np.argsort(-repeats, kind="stable"):
            r = min([int(repeats[j]), *(int(stock[k] // m) for k, m in ways[j])])
            if r <= 0:
                continue
            slots = []
            for k, m in ways[j]:
                stock[k] -= r * m
                for _ in range(m):
                    runs, want = [], r
                    while want:
                        head = lists[k][0]
                        n = min(want, head[1])
                        runs.append((head[0], n))
                        head[1] -= n
                        want -= n
                        left[head[0]] -= n
                        if not head[1]:
                            lists[k].pop(0)
                    slots.append(runs)
            ends = sorted({int(x) for runs in slots for x in np.cumsum([n for _, n in runs])})
            marks = [(np.cumsum([n for _, n in runs]), [size for size, _ in runs]) for runs in slots]
            was = 0
            for e in ends:
                lengths = tuple(sizes[int(np.searchsorted(cum, was, side="right"))] for cum, sizes in marks)
                free.setdefault(window - sum(lengths), []).append((e - was, lengths))
                was = e
    return free


def make_plan(hist: np.ndarray, window: int, grid: int = 16, least: int = 8, share: float = 0.9) -> Plan:
    """Plan from ``hist[length] = count``: full windows, sequences by least squares, and what remains of every length
    packed greedily, longest first, into the space that coarse lengths waste, then into windows of its own."""
    left = hist.astype(np.int64).copy()
    groups: list[tuple[int, tuple[int, ...]]] = []
    if left[window]:
        groups.append((int(left[window]), (window,)))
        left[window] = 0
    free = solve(left, window, grid, least, share)
    spaces = sorted(free)
    for size in range(window - 1, 0, -1):
        want = int(left[size])
        while want:
            i = bisect.bisect_left(spaces, size)
            if i < len(spaces):
                space = spaces[i]
                n, lengths = free[space].pop()
                if not free[space]:
                    del free[space]
                    spaces.pop(i)
                fit = space // size
                many = want // fit
                if many:
                    take, copies = min(n, many), fit
                else:
                    take, copies = 1, want
                if n > take:
                    _open(free, spaces, space, (n - take, lengths))
            else:
                fit = window // size
                lengths, space = (), window
                take, copies = (want // fit, fit) if want >= fit else (1, want)
            want -= take * copies
            _open(free, spaces, space - copies * size, (take, lengths + (size,) * copies))
    groups += [g for s in sorted(free) for g in free[s]]
    return Plan(window, groups)


def _open(free, spaces, space, group) -> None:
    if space not in free:
        free[space] = []
        bisect.insort(spaces, space)
    free[space].append(group)


def place(pieces: DataFrame, plan: Plan) -> DataFrame:
    """Give each piece its sequence and offset by its number among the pieces of its length."""
    spark = pieces.sparkSession
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start"), F.lit(salts(spark))).cast("int"))
    runs = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = runs.select("length", "salt", (F.sum("n").over(W.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    within = F.row_number().over(W.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32", "doc_tokens"))
    numbered = salted.withColumn("k", within).join(before, ["length", "salt"]).withColumn("number", F.col("before") + F.col("k") - 1)
    shared = spark.sparkContext.broadcast(plan.layout())

    def run(batches):
        keys, lows, bases, offsets = shared.value
        for b in batches:
            number = b["number"].to_numpy(zero_copy_only=False)
            i = np.searchsorted(keys, (b["length"].to_numpy(zero_copy_only=False).astype(np.int64) << 40) + number, side="right") - 1
            kept = [b[c] for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(bases[i] + number - lows[i]), pa.array(offsets[i])], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    return numbered.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "number").mapInArrow(run, PLACED)


def histogram(pieces: DataFrame, window: int) -> np.ndarray:
    """Counts by length; ``window`` rows at most reach the driver."""
    hist = np.zeros(window + 1, np.int64)
    for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect():
        hist[r["length"]] = r["n"]
    return hist


def pack(spark: SparkSession, docs: DataFrame, tokenizer: str, window: int = 4096, end_id: int = 2, entries: int = 400_000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Pack all documents: a row per piece with ``sequence_id`` (from 0, gapless) and ``offset``.

    Null texts count as empty: a document of the end id alone. Repeated rows are packed each; an empty
    table gives no rows; other columns are not read. Sequences pad to ``window``. The plan that goes to
    every executor is bounded by the window (lengths times combinations), not by the documents. ``entries``
    bounds a worker's dictionary of words and changes no result.
    """
    work = Workspace(spark, "packing")
    pieces = work.write(cut_documents(docs, tokenizer, window, end_id, entries, key, text), "pieces")
    return place(pieces, make_plan(histogram(pieces, window), window))

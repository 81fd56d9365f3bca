"""Benchmark decontamination with an FM-index for each shard of training text.

A shard is a run of documents of one input partition. Its words become
numbers of the benchmark's vocabulary; words outside of it and runs too short
for any phrase can't take part in a match and are replaced by one separator.
Over the rest stands an FM-index: a Burrows-Wheeler transform in a wavelet
matrix, symbol counts and suffix positions sampled at every eighth word. All
phrases of the benchmark are searched backwards at once, occurrences are
walked to the next sampled position, and the covered words are merged into
spans. No exchange is needed: the phrases (a stated query set) travel in
blocks of bounded size to the documents.

Null or empty texts have no word and no hit; null, empty or wordless items
have no phrase. Repeated documents are judged each for itself, repeated items
count by item id. An empty table gives no row. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: 0-9, a-z and bytes over 0x7F stay, A-Z is lower-cased, all else separates.
_KEEP = bytes(c if chr(c).isdigit() or 97 <= c <= 122 or c > 127 else c + 32 if 65 <= c <= 90 else 32 for c in range(128)) + bytes(range(128, 256))
SAMPLE_EVERY = 8


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_KEEP).split()


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """Positions of all suffixes in order, by doubling the compared length."""
    n = len(symbols)
    rank = np.unique(symbols, return_inverse=True)[1].astype(np.int64)
    step = 1
    while True:
        after = np.zeros(n, np.int64)
        after[:max(0, n - step)] = rank[step:] + 1
        key = rank * (n + 1) + after
        order = np.argsort(key, kind="stable")
        sorted_key = key[order]
        fresh = np.zeros(n, np.int64)
        fresh[1:] = np.cumsum(sorted_key[1:] != sorted_key[:-1])
        if fresh[-1] == n - 1:
            return order
        rank[order] = fresh
        step *= 2


class WaveletMatrix:
    """Ranks of symbols in a sequence, level by level from the highest bit."""

    def __init__(self, seq: np.ndarray, bits: int):
        self.levels = []
        for b in range(bits - 1, -1, -1):
            bit = (seq >> b) & 1
            ones = np.zeros(len(seq) + 1, np.int32)
            np.cumsum(bit, out=ones[1:])
            zeros = len(seq) - int(ones[-1])
            self.levels.append((b, ones, zeros))
            seq = np.concatenate([seq[bit == 0], seq[bit == 1]])

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol before each position."""
        low, high = np.zeros_like(at), at
        for b, ones, zeros in self.levels:
            up = ((symbol >> b) & 1).astype(bool)
            lo, hi = ones[low], ones[high]
            low = np.where(up, zeros + lo, low - lo)
            high = np.where(up, zeros + hi, high - hi)
        return high - low


class FmIndex:
    """Index of symbols below ``sigma``; the last one is 0 and occurs once, as terminator."""

    def __init__(self, symbols: np.ndarray, sigma: int):
        order = suffix_order(symbols)
        self.bwt = symbols[order - 1]  # the terminator stands before position 0
        self.before = np.concatenate([[0], np.cumsum(np.bincount(symbols, minlength=sigma))]).astype(np.int64)
        self.wavelet = WaveletMatrix(self.bwt, max(1, int(sigma - 1).bit_length()))
        self.sampled = order % SAMPLE_EVERY == 0
        self.slot = np.cumsum(self.sampled) - 1
        self.samples = order[self.sampled]

    def search(self, phrases: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Interval [low, high) of each phrase; rows are padded on the left."""
        low, high = np.zeros(len(phrases), np.int64), np.full(len(phrases), len(self.bwt), np.int64)
        width = phrases.shape[1]
        for k in range(width - 1, -1, -1):
            live = np.flatnonzero((lengths >= width - k) & (low < high))
            if not len(live):
                break
            c = phrases[live, k]
            low[live] = self.before[c] + self.wavelet.rank(c, low[live])
            high[live] = self.before[c] + self.wavelet.rank(c, high[live])
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, steps, todo, at = np.empty(len(rows), np.int64), 0, np.arange(len(rows)), rows.copy()
        while len(todo):
            done = self.sampled[at]
            out[todo[done]] = self.samples[self.slot[at[done]]] + steps
            todo, at = todo[~done], at[~done]
            c = self.bwt[at]
            at = self.before[c] + self.wavelet.rank(c, at)
            steps += 1
        return out


def phrases_of(items: list[tuple[str, str | None]], size: int, least: int = 1) -> dict:
    """Vocabulary and distinct windows of a block of items; items of fewer than ``least`` words have none."""
    vocab: dict[bytes, int] = {}
    owners: dict[tuple[int, ...], set[str]] = {}
    for item, text in items:
        ids = [vocab.setdefault(w, len(vocab) + 1) for w in words(text)]
        if len(ids) >= max(1, least):
            for i in range(max(1, len(ids) - size + 1)):
                owners.setdefault(tuple(ids[i:i + size]), set()).add(item)
    table = np.zeros((len(owners), size), np.int32)
    for row, w in zip(table, owners):
        row[size - len(w):] = w
    lengths = np.array([len(w) for w in owners], np.int64)
    return {"vocab": vocab, "table": table, "lengths": lengths, "owners": [sorted(x) for x in owners.values()]}


def match_shard(texts: list[list[bytes]], spec: dict) -> list[tuple[np.ndarray, set[str]]]:
    """For each document: its words' hits (bool), and the items found."""
    found = [(np.zeros(len(t), bool), set()) for t in texts]
    if not len(spec["lengths"]):
        return found
    get, shortest = spec["vocab"].get, int(spec["lengths"].min())
    divider = np.array([len(spec["vocab"]) + 1], np.int32)
    seqs, doc, pos = [], [], []
    for k, t in enumerate(texts):
        if len(t) < shortest:
            continue
        ids = np.fromiter(map(get, t, repeat(0)), np.int32, len(t))
        edge = np.flatnonzero(np.diff(np.concatenate([[0], ids != 0, [0]])))
        for a, b in zip(edge[::2], edge[1::2]):
            if b - a >= shortest:
                seqs += [ids[a:b], divider]
                doc.append(np.full(b - a + 1, k))
                pos.append(np.arange(a, b + 1))
    if not seqs:
        return found
    symbols, doc, pos = np.concatenate([*seqs, [0]]).astype(np.int32), np.concatenate(doc), np.concatenate(pos)
    index = FmIndex(symbols, len(spec["vocab"]) + 2)
    low, high = index.search(spec["table"], spec["lengths"])
    hit = np.flatnonzero(low < high)
    count = (high - low)[hit]
    if not len(hit):
        return found
    which = np.repeat(hit, count)
    rows = np.repeat(low[hit] - np.cumsum(count) + count, count) + np.arange(count.sum())
    start = index.locate(rows)
    mark = np.zeros(len(symbols) + 1, np.int64)
    np.add.at(mark, start, 1)
    np.add.at(mark, start + spec["lengths"][which], -1)
    for at in np.flatnonzero(np.cumsum(mark)[:-1]):
        found[doc[at]][0][pos[at]] = True
    for d, w in set(zip(doc[start].tolist(), which.tolist())):
        found[d][1].update(spec["owners"][w])
    return found


def _blocks(benchmark: DataFrame, id_col: str, text_col: str, block_chars: int) -> Iterator[list[tuple[str, str | None]]]:
    """The query set in blocks of about ``block_chars`` characters; one is on the driver at a time."""
    block, held = [], 0
    for item, text in benchmark.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")), text_col).toLocalIterator():
        block.append((item, text))
        held += len(text or "")
        if held >= block_chars:
            yield block
            block, held = [], 0
    yield block


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
                  item_text: str = "text", size: int = 10, least: int = 1, block_chars: int = 8_000_000, shard_words: int = 400_000) -> DataFrame:
    """Rows (id, n_words, spans, items) for every document.

    ``spans`` are merged runs of hit words (first word, one past the last),
    ``items`` the ids of the items found, as strings. A longer query set than
    ``block_chars`` is searched block by block, all blocks on a shard of
    documents before the next, so rows stay apart whatever their ids.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, n_words long, spans array<struct<a:long,b:long>>, items array<string>"
    spans_type = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
    blocks = _blocks(benchmark, item_col, item_text, block_chars)
    sent = [docs.sparkSession.sparkContext.broadcast(phrases_of(block, size, least)) for block in blocks]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(ids: list, texts: list[list[bytes]]) -> pa.RecordBatch:
            all_hits, all_items = [np.zeros(len(t), bool) for t in texts], [set() for _ in texts]
            for s in sent:
                for k, (hits, found) in enumerate(match_shard(texts, s.value)):
                    all_hits[k] |= hits
                    all_items[k] |= found
            spans = []
            for hits in all_hits:
                edge = np.flatnonzero(np.diff(np.concatenate([[0], hits, [0]]))).tolist()
                spans.append([{"a": a, "b": b} for a, b in zip(edge[::2], edge[1::2])])
            return pa.RecordBatch.from_arrays([pa.array(ids, id_type), pa.array(map(len, texts), pa.int64()), pa.array(spans, spans_type),
                                               pa.array(map(sorted, all_items), pa.list_(pa.string()))], names=["id", "n_words", "spans", "items"])

        for b in batches:
            id_type, ids, texts, held = b.column(0).type, [], [], 0
            for i, t in zip(b.column(0), b.column(1)):
                ids.append(i.as_py())
                texts.append(words(t.as_py()))
                held += len(texts[-1])
                if held >= shard_words:
                    yield out(ids, texts)
                    ids, texts, held = [], [], 0
            if ids:
                yield out(ids, texts)

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns."""
    return found.select(
        F.col("id").alias("doc_id"), "n_words", F.aggregate("spans", F.lit(0).cast("long"), lambda s, x: s + x.b - x.a).alias("n_hit"),
        F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
    ).withColumn("contaminated", F.col("n_hit") > 0)


def cut(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """Documents without the words of benchmark phrases; those with no other word go.

    The text between the first and the last word of a span is removed, what
    stands around it stays as it is. Rows are matched by position within the
    Python stage, so repeated ids don't matter.
    """
    size, least = options.get("size", 10), options.get("least", 1)
    blocks = list(_blocks(benchmark, options.get("item_col", "item_id"), options.get("item_text", "text"), options.get("block_chars", 8_000_000)))
    sent = [docs.sparkSession.sparkContext.broadcast(phrases_of(b, size, least)) for b in blocks]

    def without(text: str, hits: np.ndarray) -> str:
        raw = text.encode("utf-8", "surrogatepass")
        flat = np.frombuffer(raw.translate(_KEEP), np.uint8) != 32
        edge = np.flatnonzero(np.diff(np.concatenate([[0], flat, [0]])))
        first, last = edge[::2], edge[1::2]
        run = np.flatnonzero(np.diff(np.concatenate([[0], hits, [0]]))).tolist()
        out, at = [], 0
        for a, b in zip(run[::2], run[1::2]):
            out.append(raw[at:first[a]])
            at = last[b - 1]
        return b"".join([*out, raw[at:]]).decode("utf-8", "surrogatepass")

    k = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                text = part.column(k).to_pylist()
                todo = range(len(text))
                stay = [True] * len(text)
                while todo:  # what a cut brings together may match again
                    split = [words(text[i]) for i in todo]
                    hits = [np.zeros(len(s), bool) for s in split]
                    for s in sent:
                        for h, (more, _) in zip(hits, match_shard(split, s.value)):
                            h |= more
                    again = []
                    for i, h in zip(todo, hits):
                        if h.any():
                            stay[i] = not h.all()
                            text[i] = without(text[i], h)
                            if stay[i]:
                                again.append(i)
                    todo = again
                cols = [pa.array(text, part.column(k).type) if j == k else c for j, c in enumerate(part.columns)]
                yield pa.RecordBatch.from_arrays(cols, names=part.schema.names).filter(pa.array(stay, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)

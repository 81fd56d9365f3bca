"""Removal of repeated passages with run-length compressed suffix indexes.

Every string of ``length`` bytes has one anchor: the k-gram in it with the
smallest hash, the leftmost of equals. Equal strings have equal anchors at
equal places, so all copies of a string meet where their anchor is dealt to.
Windows of a document with one anchor are neighbours and form a snippet.

0. Texts are packed into homes: neighbouring rows of a few megabytes.
1. Each home announces its anchors once, with the number of its documents that
   have them; anchors of one document only are let go.
2. A home keeps where its snippets occur and sends every different snippet
   once, with its smallest document there. Snippets are dealt by anchor.
3. In each shard, snippets that are alone with their anchor are settled by
   their smallest document. Over the others, taken anchor by anchor in
   portions of bounded size, stands a run-length index: a Burrows-Wheeler
   transform stored by runs, suffix positions sampled at run ends, and for
   each class of rows that share ``length`` symbols the smallest document.
   Snippets stream through it from right to left; matching statistics of
   ``length`` or more are long matches, marked if their class has a smaller
   document.
4. Each home gets back, for a snippet, its smallest document anywhere and the
   long matches of that document's copy; it applies them to all places where
   the snippet occurs, merges overlaps and removes the bytes.

A passage in a third of all documents so costs a shard one entry for each home,
not for each document. An anchor in over ``hot`` documents is replaced by the
windows themselves, each a key of its own, so the differing surroundings of a
very common line spread over all shards instead of filling one.

Null texts are empty. Strings count by the documents they start in: rows with
the same id don't remove one another's text. Rows without an id stay whole and
remove nothing. Texts of any length are read whole, matches never cross rows.
An empty table gives no row; other columns are ignored. Snippets are told
apart by 112 bits of hashes.
"""

from __future__ import annotations

import ctypes
import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tiersort.llm.common import staged

GRAM = 24
CHUNK = 1 << 20  # bytes of text in one vectorised step; positions fit 24 bits
_U64 = np.uint64


def _mix(u: np.ndarray, count: int) -> np.ndarray:
    """Hashes of 24-grams from the 8-byte words at every position."""
    h = u[:count] * _U64(0x9E3779B97F4A7C15)
    h ^= h >> _U64(32)
    h += u[8:8 + count]
    h *= _U64(0xD6E8FEB86659FD93)
    h ^= h >> _U64(29)
    h += u[16:16 + count]
    h *= _U64(0xA0761D6478BD642F)
    h ^= h >> _U64(32)
    h *= _U64(0xE7037ED1A0B428DB)
    h ^= h >> _U64(31)
    return h


def gram_hashes(buf: bytes) -> np.ndarray:
    n = len(buf) - GRAM + 1
    if n <= 0:
        return np.zeros(0, _U64)
    padded = buf + bytes(16)
    words = np.empty(len(buf) + 8, _U64)
    for r in range(8):
        part = np.frombuffer(padded, "<u8", (len(padded) - r) // 8, r)
        words[r::8] = part[:len(words[r::8])]
    return _mix(words, n)


def anchors(buf: bytes, starts: np.ndarray, sizes: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """Snippets of texts that stand one after the other in ``buf``.

    Arrays: number of the text, first window (position in ``buf``), number of
    windows, place of the anchor within the first window, 48-bit hash.
    """
    span = length - GRAM + 1  # grams in a window
    h = gram_hashes(buf)
    n = len(buf) - length + 1
    if n <= 0:
        return tuple(np.zeros(0, np.int64) for _ in range(4)) + (np.zeros(0, _U64),)
    low = (h & ~_U64(0xFFFFFF)) | np.arange(len(h), dtype=_U64)
    width = 1
    while width * 2 <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < span:
        low = np.minimum(low[:n], low[span - width:span - width + n])
    at = (low[:n] & _U64(0xFFFFFF)).astype(np.int64)
    owner = np.repeat(np.arange(len(sizes)), sizes)[:n]
    fits = np.zeros(len(buf) + 1, np.int8)
    whole = sizes >= length
    np.add.at(fits, starts[whole], 1)
    np.add.at(fits, starts[whole] + sizes[whole] - length + 1, -1)
    fits = np.cumsum(fits[:n], dtype=np.int8) > 0
    head = fits.copy()
    head[1:] &= (at[1:] != at[:-1]) | (owner[1:] != owner[:-1]) | ~fits[:-1]
    first = np.flatnonzero(head)
    stop = np.flatnonzero(fits & np.concatenate([head[1:] | ~fits[1:], [True]]))
    return owner[first], first, stop - first + 1, at[first] - first, h[at[first]] >> _U64(16)


def _pack(*arrays: np.ndarray) -> bytes:
    """Arrays of integers, byte plane by byte plane (small numbers cost little), compressed."""
    out = [len(arrays).to_bytes(2, "little")]
    for a in arrays:
        x = a.astype("<u8").view(np.uint8).reshape(-1, 8)
        used = next((k for k in range(8, 0, -1) if len(x) and x[:, k - 1].any()), 0)
        out += [len(a).to_bytes(6, "little"), used.to_bytes(1, "little"), np.ascontiguousarray(x[:, :used].T).tobytes()]
    return zstandard.ZstdCompressor(level=1).compress(b"".join(out))


def _unpack(blob: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    out, at = [], 2
    for _ in range(int.from_bytes(raw[:2], "little")):
        n, used = int.from_bytes(raw[at:at + 6], "little"), raw[at + 6]
        x = np.zeros((n, 8), np.uint8)
        x[:, :used] = np.frombuffer(raw, np.uint8, n * used, at + 7).reshape(used, n).T
        out.append(x.reshape(-1).view("<u8").astype(_U64))
        at += 7 + n * used
    return out


def _steps(x: np.ndarray) -> np.ndarray:
    """Differences of an ascending array."""
    return np.diff(x, prepend=x.dtype.type(0))


def _shard(h: np.ndarray, shards: int) -> np.ndarray:
    """Shard of a 48-bit hash, mixed once more: anchors are minima, so their hashes crowd at the low end."""
    return ((h * _U64(0x9E3779B97F4A7C15) >> _U64(32)) * _U64(shards) >> _U64(32)).astype(np.int32)


def _give_back() -> None:
    """Returns freed memory to the system, so that a reused worker doesn't keep what its largest group took."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


class RunLengthIndex:
    """Index over snippets given in ascending order of their smallest document.

    Symbols are bytes plus 2; 1 divides snippets, 0 ends the text. Kept of the
    Burrows-Wheeler transform are its runs (symbol, first row) and the suffix
    positions at the runs' ends.
    """

    def __init__(self, snippets: list[bytes], docs: np.ndarray, length: int):
        sizes = np.fromiter(map(len, snippets), np.int64, len(snippets))
        text = np.ones(int(sizes.sum()) + len(snippets) + 1, np.int16)
        self.start = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]]) if len(snippets) else np.zeros(0, np.int64)
        inside = np.ones(len(text), bool)
        inside[np.cumsum(sizes + 1) - 1] = False
        inside[-1] = False
        text[inside] = np.frombuffer(b"".join(snippets), np.uint8).astype(np.int16) + 2
        text[-1] = 0
        self.text, self.length, n = text, length, len(text)
        order, near, depth = suffix_rows(text, length)
        bwt = text[order - 1]
        head = np.flatnonzero(np.concatenate([[True], bwt[1:] != bwt[:-1]]))
        self.run_start, self.run_symbol = head, bwt[head].astype(np.int64)
        ends = np.append(head[1:], n) - 1
        self.first_sample, self.last_sample = order[head].astype(np.int64), order[ends].astype(np.int64)
        self.before = np.concatenate([[0], np.cumsum(np.bincount(bwt, minlength=258))])
        del bwt
        size = ends - head + 1
        self.run_of = np.repeat(np.arange(len(head), dtype=np.int32), size)  # directory of rows
        by_symbol = np.argsort(self.run_symbol, kind="stable")  # runs of a symbol together, in order
        inner = np.cumsum(size[by_symbol]) - size[by_symbol]
        self.run_rank = np.empty(len(head), np.int64)  # symbols like the run's before it
        first = np.searchsorted(self.run_symbol[by_symbol], np.arange(258))
        zero = np.append(inner, n)[np.minimum(first, len(inner))]
        self.run_rank[by_symbol] = inner - zero[self.run_symbol[by_symbol]]
        self.by_symbol, self.symbol_first = by_symbol, np.searchsorted(self.run_symbol[by_symbol], np.arange(259))
        self.run_stop = np.append(head[1:], n)
        self.run_key = self.run_symbol[by_symbol] * (len(head) + 1) + by_symbol  # ascending
        # classes of rows with the same ``length`` symbols, none of them a divider
        cut = np.flatnonzero(text < 2)
        room = np.repeat(cut, np.diff(cut, prepend=-1)).astype(np.int32) - np.arange(n, dtype=np.int32)
        alike = np.zeros(n, bool)
        full = room[order] >= length
        del room
        pair = np.flatnonzero(full[1:] & full[:-1]) + 1
        if depth:  # ranks by ``depth`` symbols: equal at a place and a little further on
            one, two, on = order[pair], order[pair - 1], length - depth
            alike[pair] = (near[one] == near[two]) & (near[one + on] == near[two + on])
        self.class_start = np.flatnonzero(~alike)
        self.class_of = np.cumsum(~alike, dtype=np.int32) - np.int32(1)
        owner = np.searchsorted(self.start, order, side="right") - 1
        self.class_doc = np.minimum.reduceat(np.append(docs, 0)[np.minimum(owner, len(docs))], self.class_start) if n else docs

    def left(self, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Symbol in front of each row, and the row that starts there."""
        run = self.run_of[row]
        c = self.run_symbol[run]
        return c, self.before[c] + self.run_rank[run] + row - self.run_start[run]

    def _common(self, pattern: np.ndarray, at: np.ndarray, sizes: np.ndarray, pos: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Symbols that the pattern from ``at`` and the text from ``pos`` share, up to ``most``."""
        out = np.zeros(len(at), np.int64)
        live = np.flatnonzero(most > 0)
        while len(live):
            same = self.text[np.minimum(pos[live] + out[live], len(self.text) - 1)] == pattern[at[live] + out[live]]
            live = live[same]
            out[live] += 1
            live = live[out[live] < most[live]]
        return out

    def statistics(self, patterns: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Matching statistics, streamed from right to left over all patterns at once.

        Flat arrays over the patterns' symbols: length of the longest match
        that starts there, a row and a text position of it.
        """
        sizes = np.fromiter(map(len, patterns), np.int64, len(patterns))
        flat = np.frombuffer(b"".join(patterns), np.uint8).astype(np.int16) + 2
        end = np.cumsum(sizes)
        length, rows, places = (np.zeros(len(flat), np.int32) for _ in range(3))
        row, pos, size = np.zeros(len(sizes), np.int64), np.full(len(sizes), len(self.text) - 1), np.zeros(len(sizes), np.int64)
        for step in range(1, int(sizes.max(initial=0)) + 1):
            live = np.flatnonzero(sizes >= step)
            at = end[live] - step
            c, r = flat[at].astype(np.int64), row[live]
            run = self.run_of[r].astype(np.int64)
            other = np.flatnonzero(self.run_symbol[run] != c)
            if len(other):  # no match to extend: the nearest run of the symbol above or below goes on, whichever matches longer
                q, want = live[other], c[other]
                had = size[q].copy()
                a, b = self.symbol_first[want], self.symbol_first[want + 1]
                # runs of one symbol are ascending: count those before the row's run
                key = want * (len(self.run_start) + 1) + run[other]
                below = np.searchsorted(self.run_key, key)
                best = np.full(len(q), -1, np.int64)
                found = np.full(len(q), -1, np.int64)
                for which, ok, sample in ((below - 1, below > a, self.last_sample), (below, below < b, self.first_sample)):
                    k = np.flatnonzero(ok)
                    target = self.by_symbol[which[k]]
                    got = self._common(flat, at[other][k] + 1, sizes, sample[target], had[k])
                    better = got > best[k]
                    k, target, got = k[better], target[better], got[better]
                    best[k], found[k] = got, target
                    first = sample is self.first_sample
                    row[q[k]] = self.run_start[target] if first else self.run_stop[target] - 1
                    pos[q[k]] = sample[target]
                    size[q[k]] = got
                none = q[found < 0]  # a symbol the text lacks
                row[none], pos[none], size[none] = 0, len(self.text) - 1, -1
            fine = live[size[live] >= 0]
            _, row[fine] = self.left(row[fine])
            pos[fine] -= 1
            size[live] += 1
            length[at], rows[at], places[at] = size[live], row[live], pos[live]
        return length, rows, places

    def smallest(self, rows: np.ndarray) -> np.ndarray:
        """Smallest document of the class of each row."""
        return self.class_doc[self.class_of[rows]]


def suffix_rows(text: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray | None, int]:
    """Suffix positions in order, by doubling from packs of six symbols.

    Also ranks by the largest compared number of symbols up to ``length``, and
    that number: 0 if all suffixes differ before it reaches half of ``length``.
    """
    n = len(text)
    padded = np.concatenate([text, np.zeros(6, np.int16)])
    key = np.zeros(n, np.int64)
    for k in range(6):
        key *= 512
        key += padded[k:k + n]
    step, near, depth = 6, None, 0
    while True:
        order = np.argsort(key).astype(np.int32)
        ranked = key[order]
        fresh = np.zeros(n, np.int32)
        np.cumsum(ranked[1:] != ranked[:-1], out=fresh[1:], dtype=np.int32)
        rank = np.empty(n, np.int32)
        rank[order] = fresh
        if step <= length < 2 * step:
            near, depth = rank, step
        if n == 0 or fresh[-1] == n - 1:
            return order, near, depth
        key = rank.astype(np.int64)
        key *= n + 1
        key[:max(0, n - step)] += rank[step:]
        key[:max(0, n - step)] += 1
        step *= 2


def _homes(docs: DataFrame, home_bytes: int) -> DataFrame:
    """Rows (home, n_bytes, rows, z) of neighbouring texts: their ids and sizes, and all their bytes, compressed."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, ids, texts, held = TaskContext.get().partitionId(), 0, [], [], 0

        def full() -> pa.RecordBatch:
            sizes = np.fromiter(map(len, texts), np.int64, len(texts))
            return pa.RecordBatch.from_arrays([
                pa.array([part << 32 | number], pa.int64()), pa.array([held], pa.int64()), pa.array([_pack(_steps(np.array(ids, np.int64).view(_U64)), sizes)], pa.binary()),
                pa.array([zstandard.ZstdCompressor(level=1).compress(b"".join(texts))], pa.binary())], names=["home", "n_bytes", "rows", "z"])

        for b in batches:
            for at in range(0, b.num_rows, 500):
                for i, t in zip(b.column(0).slice(at, 500).to_pylist(), b.column(1).slice(at, 500).to_pylist()):
                    ids.append(i)
                    texts.append(t)
                    held += len(t)
                    if held >= home_bytes:
                        yield full()
                        number, ids, texts, held = number + 1, [], [], 0
        if ids:
            yield full()

    return docs.mapInArrow(run, "home long, n_bytes long, rows binary, z binary")


def _texts(rows: bytes, z: bytes) -> tuple[np.ndarray, list[bytes]]:
    """Ids and texts of a home."""
    ids, sizes = _unpack(rows)
    raw, end = zstandard.ZstdDecompressor().decompress(z), np.cumsum(sizes.astype(np.int64)).tolist()
    return np.cumsum(ids).view(np.int64), [raw[a:b] for a, b in zip([0, *end], end)]


def _chunks(texts: list[bytes]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about CHUNK bytes; a longer text stands alone."""
    at, held = 0, 0
    for i, t in enumerate(texts):
        if held and held + len(t) > CHUNK:
            yield at, i
            at, held = i, 0
        held += len(t)
    if at < len(texts):
        yield at, len(texts)


def _snippets(texts: list[bytes], length: int) -> Iterator[tuple[np.ndarray, ...]]:
    """As ``anchors``, with positions within each text; texts over a chunk go in overlapping parts."""
    part = CHUNK
    for a, b in _chunks(texts):
        if b == a + 1 and len(texts[a]) > part:
            t = texts[a]
            for at in range(0, len(t) - length + 1, part - length + 1):  # windows of neighbouring parts don't overlap
                piece = t[at:at + part]
                _, first, n, place, h = anchors(piece, np.zeros(1, np.int64), np.array([len(piece)]), length)
                yield np.full(len(first), a), first + at, n, place, h
            continue
        sizes = np.fromiter(map(len, texts[a:b]), np.int64, b - a)
        starts = np.cumsum(sizes) - sizes
        who, first, n, place, h = anchors(b"".join(texts[a:b]), starts, sizes, length)
        yield who + a, first - starts[who], n, place, h


def _distinct(h: np.ndarray, who: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different hashes in order, and the number of documents of each (at most 255)."""
    order = np.argsort(h, kind="stable")
    h, who = h[order], who[order]
    head = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
    fresh = np.concatenate([[True], (h[1:] != h[:-1]) | (who[1:] != who[:-1])])
    return h[head], np.minimum(255, np.add.reduceat(fresh, head, dtype=np.int64))


def _portions(anchor: np.ndarray, size: np.ndarray, most: int) -> Iterator[np.ndarray]:
    """Snippets (numbers) in portions of about ``most`` bytes; those of one anchor stay together."""
    order = np.argsort(anchor, kind="stable")
    head = np.flatnonzero(np.concatenate([[True], anchor[order][1:] != anchor[order][:-1]]))
    room = np.add.reduceat(size[order], head)
    at, held = 0, 0
    for k, (a, n) in enumerate(zip(head.tolist(), room.tolist())):
        if held and held + n > most:
            yield order[at:a]
            at, held = a, 0
        held += n
    yield order[at:]


def _steps_of(shards: int, meets: int, length: int, hot: int, index_bytes: int, with_text: bool) -> tuple:
    """The functions of the steps, for ``meets`` shards of announced anchors and ``shards`` of snippets."""
    def announce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for home, rows, z in zip(b.column(0).to_pylist(), b.column(1), b.column(2)):
                ids, texts = _texts(rows.as_py(), z.as_py())
                found = [(h, who) for who, _, _, _, h in _snippets(texts, length)]
                if not any(len(h) for h, _ in found):
                    continue
                names = np.unique(ids, return_inverse=True)[1].astype(np.int32)
                h, count = _distinct(np.concatenate([h for h, _ in found]), names[np.concatenate([w for _, w in found])])
                shard = _shard(h, meets)
                order = np.argsort(shard, kind="stable")  # hashes stay ascending
                h, count, edge = h[order], count[order], np.searchsorted(shard[order], np.arange(meets + 1))
                out = [(k, _pack(_steps(h[a:b]), count[a:b])) for k, (a, b) in enumerate(zip(edge, edge[1:])) if b > a]
                yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in out], pa.int32()), pa.array([home] * len(out), pa.int64()), pa.array([x for _, x in out], pa.binary())],
                                                 names=["shard", "home", "blob"])
            _give_back()

    def meet(key: tuple, blobs: pd.DataFrame) -> pd.DataFrame:
        """Anchors in more than one document, back to the homes that have them."""
        got = [_unpack(blob) for blob in blobs["blob"]]
        home = np.repeat(np.arange(len(got), dtype=np.int32), [len(h) for h, _ in got])
        h, count = np.concatenate([np.cumsum(h) for h, _ in got]), np.concatenate([c for _, c in got]).astype(np.int64)
        del got
        order = np.argsort(h, kind="stable")
        h, count, home = h[order], count[order], home[order]
        head = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
        total = np.repeat(np.add.reduceat(count, head), np.diff(np.append(head, len(h))))
        keep = total > 1
        h, home, very = h[keep], home[keep], total[keep] > hot
        order = np.argsort(home, kind="stable")  # hashes stay ascending
        h, home, very = h[order], home[order], very[order].astype(np.int64)
        edge, names = np.searchsorted(home, np.arange(len(blobs) + 1)), blobs["home"].tolist()
        out = [(names[k], _pack(_steps(h[a:b]), very[a:b])) for k, (a, b) in enumerate(zip(edge, edge[1:])) if b > a]
        _give_back()
        return pd.DataFrame(out, columns=["home", "blob"]).astype({"home": "int64"})

    sent = {"shard": "int32", "home": "int64", "blob": object, "bytes": object}

    def gather(key: tuple, group: pd.DataFrame, blobs: pd.DataFrame) -> pd.DataFrame:
        """Snippets of a home around anchors that recur: where they are (shard -1), and each once to its shard."""
        nothing = pd.DataFrame({k: pd.Series([], dtype=t) for k, t in sent.items()})
        if not len(group) or not len(blobs):
            return nothing
        ids, texts = _texts(group["rows"].iloc[0], group["z"].iloc[0])
        told = [_unpack(blob) for blob in blobs["blob"]]
        wanted, very = np.concatenate([np.cumsum(h) for h, _ in told]), np.concatenate([v for _, v in told])
        order = np.argsort(wanted)
        wanted, very = wanted[order], very[order]
        table: dict[tuple[int, bytes], int] = {}
        snippet, place, hashes, use, who_, first_ = [], [], [], [], [], []
        for who, first, n, off, h in _snippets(texts, length):
            at = np.minimum(np.searchsorted(wanted, h), len(wanted) - 1)
            hit = np.flatnonzero(wanted[at] == h)
            for w, f, k, o, x, is_hot in zip(who[hit].tolist(), first[hit].tolist(), n[hit].tolist(), off[hit].tolist(), h[hit].tolist(), very[at[hit]].tolist()):
                t = texts[w]
                # a very common anchor: every window for itself, keyed by all of its bytes
                for f, s, o, x in ([(f, t[f:f + k + length - 1], o, x)] if not is_hot else
                                   [(f + j, y := t[f + j:f + j + length], 255, xxhash.xxh3_64_intdigest(y) >> 16) for j in range(k)]):
                    u = table.setdefault((o, s), len(snippet))
                    if u == len(snippet):
                        snippet.append(s)
                        place.append(o)
                        hashes.append(x)
                    use.append(u)
                    who_.append(w)
                    first_.append(f)
        if not snippet:
            return nothing
        del table
        use, who_, first_ = np.array(use, np.int32), np.array(who_, np.int32), np.array(first_, np.int64)
        size = np.fromiter(map(len, snippet), np.int64, len(snippet))
        doc = ids[who_]
        least, most = np.full(len(snippet), np.iinfo(np.int64).max), np.full(len(snippet), np.iinfo(np.int64).min)
        np.minimum.at(least, use, doc)
        np.maximum.at(most, use, doc)
        order = np.argsort(use, kind="stable")
        out = [(-1, key[0], _pack(size, _steps(use[order].astype(_U64)), who_[order], first_[order]), None)]
        del use, who_, first_, doc
        hashes, place = np.array(hashes, _U64), np.array(place, np.uint8)
        shard = _shard(hashes, shards)
        order = np.argsort(shard, kind="stable")
        edge = np.searchsorted(shard[order], np.arange(shards + 1))
        press = zstandard.ZstdCompressor(level=3)
        for k in np.flatnonzero(np.diff(edge)).tolist():
            own = order[edge[k]:edge[k + 1]]
            out.append((k, key[0], _pack(_steps(own.astype(_U64)), place[own], size[own], hashes[own], least[own].view(_U64), most[own] > least[own]),
                        press.compress(b"".join([snippet[i] for i in own.tolist()]))))
        _give_back()
        return pd.DataFrame(out, columns=list(sent)).astype({"shard": "int32", "home": "int64"})

    def settle(key: tuple, blobs: pd.DataFrame) -> pd.DataFrame:
        """For the snippets of a shard their smallest document and the long matches of its copy, back to the homes."""
        number: dict[tuple[int, int, int], int] = {}
        text, anchor, u_, local_, doc_, many_ = [], [], [], [], [], []
        for blob, raw in zip(blobs["blob"], blobs["bytes"]):
            local, place, size, h, doc, many = _unpack(blob)
            raw, end = zstandard.ZstdDecompressor().decompress(raw), np.cumsum(size.astype(np.int64)).tolist()
            at, mine = 0, np.empty(len(place), np.int64)
            for i, (e, o, x) in enumerate(zip(end, place.tolist(), h.tolist())):
                s = raw[at:e]
                at = e
                u = number.setdefault((x, o, xxhash.xxh3_64_intdigest(s)), len(text))
                if u == len(text):
                    text.append(s)
                    anchor.append(x << 1 | (o == 255))
                mine[i] = u
            u_.append(mine)
            local_.append(np.cumsum(local))
            doc_.append(doc.view(np.int64))
            many_.append(many > 0)
        del number
        u, doc = np.concatenate(u_), np.concatenate(doc_)
        least = np.full(len(text), np.iinfo(np.int64).max)
        np.minimum.at(least, u, doc)
        size = np.fromiter(map(len, text), np.int64, len(text))
        anchor = np.array(anchor, _U64)
        _, inv, count = np.unique(anchor, return_inverse=True, return_counts=True)
        mixed = np.flatnonzero(count[inv] > 1)
        owner_, place_ = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for part in _portions(anchor[mixed], size[mixed], index_bytes) if len(mixed) else ():
            part = mixed[part]
            part = part[np.argsort(least[part], kind="stable")]
            pieces = [text[i] for i in part.tolist()]
            index = RunLengthIndex(pieces, least[part], length)
            long, rows_, _ = index.statistics(pieces)
            start = np.cumsum(size[part]) - size[part]
            at = np.flatnonzero(long >= length)
            owner = np.searchsorted(start, at, side="right") - 1
            hit = index.smallest(rows_[at]) < least[part][owner]
            owner_.append(part[owner[hit]])
            place_.append((at - start[owner])[hit])
            del index, long, rows_
        owner, place = np.concatenate(owner_), np.concatenate(place_)
        order = np.lexsort((place, owner))
        owner, place = owner[order], place[order]
        hits = np.bincount(owner, minlength=len(text))
        begin = np.cumsum(hits) - hits
        out = []
        for home, mine, local, doc, many in zip(blobs["home"].tolist(), u_, local_, doc_, many_):
            here = least[mine] == doc  # the snippet's smallest document is in this home
            tell = np.flatnonzero(many | ~here | (hits[mine] > 0))
            if len(tell):
                n = np.where(here[tell], hits[mine[tell]], 0)
                at = np.repeat(begin[mine[tell]] - np.cumsum(n) + n, n) + np.arange(n.sum())
                out.append((home, _pack(_steps(local[tell]), least[mine[tell]].view(_U64), n, place[at])))
        _give_back()
        return pd.DataFrame(out, columns=["home", "blob"]).astype({"home": "int64"})

    def finish(key: tuple, group: pd.DataFrame, said: pd.DataFrame) -> pd.DataFrame:
        names = ["id", "n_bytes", "spans", "kept_sha256", *["kept"] * with_text]
        if not len(group):
            return pd.DataFrame({n: pd.Series([], dtype=object) for n in names})
        ids, texts = _texts(group["rows"].iloc[0], group["z"].iloc[0])
        who, first, stop = (np.zeros(0, np.int64) for _ in range(3))
        kept_, told = said["blob"][said["kept"]].tolist(), [_unpack(x) for x in said["blob"][~said["kept"]]]
        if kept_ and told:
            size, use, at, place = (x.astype(np.int64) for x in _unpack(kept_[0]))
            use = np.cumsum(use)
            local, least, n, hit = (np.concatenate(x) for x in zip(*[(np.cumsum(a).astype(np.int64), b.view(np.int64), c.astype(np.int64), d.astype(np.int64)) for a, b, c, d in told]))
            low = np.full(len(size), np.iinfo(np.int64).max)
            low[local] = least
            hits, begin = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
            hits[local], begin[local] = n, np.cumsum(n) - n
            later = ids[at] > low[use]
            own = np.flatnonzero((ids[at] == low[use]) & (hits[use] > 0))
            reps = hits[use[own]]
            k = np.repeat(begin[use[own]] - np.cumsum(reps) + reps, reps) + np.arange(reps.sum())
            who = np.concatenate([at[later], np.repeat(at[own], reps)])
            first = np.concatenate([place[later], np.repeat(place[own], reps) + hit[k]])
            stop = first + np.concatenate([size[use[later]], np.full(len(k), length)])
        order = np.lexsort((first, who))
        who, first, stop = who[order], first[order], stop[order]
        edge = np.searchsorted(who, np.arange(len(ids) + 1))
        out = []
        for i, t in enumerate(texts):
            spans: list[list[int]] = []
            for a, b in zip(first[edge[i]:edge[i + 1]].tolist(), stop[edge[i]:edge[i + 1]].tolist()):
                if spans and a <= spans[-1][1]:
                    spans[-1][1] = max(b, spans[-1][1])
                else:
                    spans.append([a, b])
            kept, at = [], 0
            for a, b in spans:
                kept.append(t[at:a])
                at = b
            kept = b"".join([*kept, t[at:]])
            out.append((int(ids[i]), len(t), [{"a": a, "b": b} for a, b in spans], hashlib.sha256(kept).hexdigest(), *[kept] * with_text))
        _give_back()
        return pd.DataFrame(out, columns=names)

    return announce, meet, gather, settle, finish


def repeated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 50, hot: int = 20_000,
             shard_bytes: int = 3 << 19, with_text: bool = False) -> DataFrame:
    """Rows (id, n_bytes, spans, kept_sha256[, kept]) for every document row.

    ``spans`` are the maximal removed byte runs (start, end); ``kept`` the
    bytes that stay. ``shard_bytes`` of text give a shard of snippets; homes
    take twice, portions of an index a third of it.
    """
    if length < GRAM + 1:
        raise ValueError(f"length over {GRAM}")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("binary"), F.lit(b"")).alias("t"))
    schema = "id long, n_bytes long, spans array<struct<a:long,b:long>>, kept_sha256 string" + ", kept binary" * with_text
    homes = staged(_homes(rows.where("id is not null"), 2 * shard_bytes), "homes")
    total = homes.agg(F.sum("n_bytes")).first()[0] or 0
    shards, meets = max(1, -(-total // shard_bytes)), max(1, -(-total // (8 * shard_bytes)))
    announce, meet, gather, settle, finish = _steps_of(shards, meets, length, hot, shard_bytes // 3, with_text)
    texts = homes.select("home", "rows", "z")
    told = texts.mapInArrow(announce, "shard int, home long, blob binary").groupBy("shard").applyInPandas(meet, "home long, blob binary")
    sent = staged(texts.groupBy("home").cogroup(told.groupBy("home")).applyInPandas(gather, "shard int, home long, blob binary, bytes binary"), "snippets")
    back = staged(sent.where("shard >= 0").groupBy("shard").applyInPandas(settle, "home long, blob binary"), "marks")
    said = back.withColumn("kept", F.lit(False)).unionByName(sent.where("shard < 0").select("home", "blob", F.lit(True).alias("kept")))
    done = texts.groupBy("home").cogroup(said.groupBy("home")).applyInPandas(finish, schema)
    alone = rows.where("id is null").select("id", F.octet_length("t").cast("long").alias("n_bytes"), F.array().cast("array<struct<a:bigint,b:bigint>>").alias("spans"),
                                            F.sha2("t", 256).alias("kept_sha256"), *[F.col("t").alias("kept")] * with_text)
    return done.unionByName(alone)


def digest(found: DataFrame) -> DataFrame:
    return found.select(F.col("id").alias("doc_id"), "n_bytes", F.aggregate("spans", F.lit(0).cast("long"), lambda s, x: s + x.b - x.a).alias("n_removed"),
                        F.size("spans").cast("long").alias("n_spans"), "kept_sha256")

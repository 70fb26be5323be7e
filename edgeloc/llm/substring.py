"""Substring dedup by repeated-phrase automata.

A window is `window_words` consecutive words; it recurs if its sequence starts in two documents or more. Four steps:

1. Propose: each task hashes the windows of its documents (64 bits, besides the bucket, which comes from another
   hash of the same words), keeps one entry for a window that it saw in several documents, and sends hashes and places, packed by
   bucket. A bucket's task finds hashes that recur and the place in the smallest document that has each.
2. Confirm: places of a document that follow its owner's places form segments; the owner's shard cuts its words there, and
   the document's shard compares word by word. Only what is equal is a recurring passage: a hash never removes a word.
3. Compile: each shard writes the passages confirmed for its documents into an Aho-Corasick automaton with pyahocorasick. Words are
   written in a few symbols of a small alphabet, since a node's branches are searched one by one.
4. Stream: every document runs through its shard's automaton; its matches alone, where a smaller document owns the passage, say which words go.

All shuffles are packed numbers but one of the texts, also packed, and one of owners' words; all work is linear. A window in a third of all
documents costs one entry for each task in its bucket, since tasks settle its repeats themselves.

What a hash can do: if two different windows share its 64 bits and a bucket, the comparison drops the false pair, and a true repeat of the larger
one may stay. No words are ever removed without an equal window in a smaller document.

Defined results: null text has no words; a document with fewer words than a window keeps all; a null id is never
smaller than another and loses no words; rows with the same id are one document to the comparison, but each keeps its row; an
empty table gives an empty one; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, shuffle_partitions

PACKED = "bucket int, docs binary, at binary, hashes binary, firsts binary, delta binary"
TOLD = "bucket int, kind int, docs binary, at binary, until binary, firsts binary, delta binary, words binary"
_SEGMENT, _REQUEST, _PHRASE = 1, 2, 3
_FLUSH = 1_000_000  # windows that a task packs at a time
_SLICE = 1 << 20  # bytes of text hashed at a time
_SHARD = 64 << 20  # bytes of text in a shard, at most, on average
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_BYTE = np.random.default_rng(13).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE[_BLANK] = 0
_PLACE = np.random.default_rng(31).integers(1, 1 << 63, 1 << 16, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _mix(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each word of some texts in their order, and the text that it is in."""
    texts = pa.concat_arrays([texts.cast(pa.large_binary()).fill_null(b"")])
    offsets = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8)
    data = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    if not len(data):
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    there = ~_BLANK[data]
    fresh = np.concatenate(([True], ~there[:-1]))
    fresh[offsets[:-1][offsets[:-1] < len(data)]] = True
    starts = np.flatnonzero(there & fresh)
    if not len(starts):
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    data = data[starts[0] :]
    place = np.arange(len(data)) - np.repeat(starts - starts[0], np.diff(starts, append=starts[0] + len(data)))
    factor = _PLACE[place & 0xFFFF]
    far = np.flatnonzero(place > 0xFFFF)
    if len(far):  # in words beyond 64 KiB a byte's factor tells all of its place
        factor[far] = _mix(factor[far] + (place[far] >> 16).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    h = np.add.reduceat(_BYTE[data] * factor, starts - starts[0])
    return _mix(h), np.searchsorted(offsets, starts, side="right") - 1


def window_hashes(words: np.ndarray, text: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First word of each window inside one text, its hash, and another hash that gives its bucket."""
    n = len(words) - size + 1
    if n < 1:
        return np.empty(0, np.int64), np.empty(0, np.uint64), np.empty(0, np.uint64)
    h = np.full(n, 0x9E3779B97F4A7C15, dtype=np.uint64)
    for k in range(size):
        h += words[k : k + n]
        h *= np.uint64(0x9FB21C651E98DF25)
        h ^= h >> np.uint64(31)
    at = np.flatnonzero(text[:n] == text[size - 1 :])
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(words)))
    return at, _mix(h[at]), _mix(total[at + size] - total[at])


def _pack(x: np.ndarray) -> bytes:
    """First value and differences, in the narrowest type that holds them."""
    x = np.asarray(x, dtype=np.int64)
    step = np.diff(x)
    wide = max(abs(int(step.min(initial=0))), abs(int(step.max(initial=0))))
    kind = "i1" if wide < 1 << 7 else "<i2" if wide < 1 << 15 else "<i4" if wide < 1 << 31 else "<i8"
    return kind[-1].encode() + x[:1].tobytes() + zstandard.compress(step.astype(kind).tobytes(), 1)


def _unpack(x: bytes) -> np.ndarray:
    step = np.frombuffer(zstandard.decompress(x[9:]), "i1" if x[:1] == b"1" else f"<i{x[:1].decode()}")
    return np.cumsum(np.concatenate((np.frombuffer(x[1:9], np.int64), step)), dtype=np.int64)


def _small(to: np.ndarray) -> np.ndarray:
    return to.astype(np.uint16) if not len(to) or to.max() < 1 << 16 else to.astype(np.int32)  # two bytes sort fastest


def _groups(*sorted_keys: np.ndarray) -> np.ndarray:
    """Where a group of equal keys starts."""
    return np.flatnonzero(np.concatenate(([True], np.logical_or.reduce([k[1:] != k[:-1] for k in sorted_keys])))) if len(sorted_keys[0]) else np.empty(0, np.int64)


def _by_bucket(to: np.ndarray, docs: np.ndarray, at: np.ndarray, hashes: np.ndarray | None, firsts: np.ndarray | None = None, delta: np.ndarray | None = None) -> pa.RecordBatch:
    order = np.argsort(_small(to), kind="stable")
    to = to[order]
    cuts = _groups(to)
    parts = list(zip(cuts, np.concatenate((cuts[1:], [len(to)]))))

    def packed(x, write):
        return pa.nulls(len(cuts), pa.binary()) if x is None else pa.array([write(y[s:e]) for y in (x[order],) for s, e in parts], type=pa.binary())

    return pa.RecordBatch.from_arrays([pa.array(to[cuts].astype(np.int32)), packed(docs, _pack), packed(at, _pack), packed(hashes, np.ndarray.tobytes), packed(firsts, _pack), packed(delta, _pack)], names=["bucket", "docs", "at", "hashes", "firsts", "delta"])


def _shard_of(docs: np.ndarray, shards: int) -> np.ndarray:
    return (_mix(docs.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(7)) % np.uint64(shards)).astype(np.int64)


def _leads(hashes: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each distinct hash the first entry of its smallest doc; and for each entry that one of its hash."""
    order = np.argsort(hashes)
    h = hashes[order]
    start = np.concatenate(([True], h[1:] != h[:-1]))
    place = np.empty(len(h), np.int64)
    place[order] = np.cumsum(start) - 1
    own = np.flatnonzero(np.minimum.reduceat(docs[order], np.flatnonzero(start))[place] == docs)
    lead = np.empty(int(start.sum()), np.int64)
    lead[place[own[::-1]]] = own[::-1]
    return lead, lead[place]


def _slices(batch: pa.RecordBatch, column: int) -> Iterator[pa.RecordBatch]:
    step = max(1, int(batch.num_rows * _SLICE / max(_SLICE, batch.column(column).nbytes)))
    for at in range(0, batch.num_rows, step):
        yield batch.slice(at, step)


def _repeats(docs: np.ndarray, at: np.ndarray, lead: np.ndarray, own: bool = False) -> tuple[np.ndarray, ...] | None:
    """(docs, at, firsts, delta) of entries whose hash a smaller document has, with own also those that their document has at its lead; delta leads to that place."""
    again = np.flatnonzero((docs[lead] < docs) | (own & (docs[lead] == docs) & (lead != np.arange(len(lead)))))
    return (docs[again], at[again], docs[lead[again]], at[lead[again]] - at[again]) if len(again) else None


def _propose(rows: DataFrame, size: int, shards: int) -> DataFrame:
    """Packed (docs, at, firsts, delta) by shard of the document: places whose hash a smaller document has too."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        count = 0

        def flush():
            docs, place, a, b = (np.concatenate(x) for x in zip(*held))
            once, lead = _leads(a, docs)
            once.sort()  # one entry for each window goes on; its repeats in this task are settled here
            yield _by_bucket((b[once] % np.uint64(shards)).astype(np.int64), docs[once], place[once], a[once])
            found = _repeats(docs, place, lead, own=True)
            if found:
                yield _by_bucket(_shard_of(found[0], shards), *found[:2], None, *found[2:])

        for batch in batches:
            for part in _slices(batch.filter(batch.column(0).is_valid()), 1):
                words, text = word_hashes(part.column(1))
                at, a, b = window_hashes(words, text, size)
                if len(at):
                    base = np.searchsorted(text, np.arange(len(part)))
                    held.append((part.column(0).to_numpy()[text[at]], at - base[text[at]], a, b))
                    count += len(at)
                if count >= _FLUSH:
                    yield from flush()
                    held, count = [], 0
        if held:
            yield from flush()

    def recurring(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come bucket by bucket; what a task finds is packed by shard over all of its buckets."""
        sent: list[tuple[np.ndarray, ...]] = []
        found: list[tuple[np.ndarray, ...]] = []
        bucket = None

        def settle():
            docs, at, hashes = (np.concatenate(x) for x in zip(*sent))
            sent.clear()
            again = _repeats(docs, at, _leads(hashes, docs)[1])
            if again:
                found.append(again)

        def told():
            docs, at, firsts, delta = (np.concatenate(x) for x in zip(*found))
            found.clear()
            return _by_bucket(_shard_of(docs, shards), docs, at, None, firsts, delta)

        for b in batches:
            settled = b.column(4).is_valid()  # repeats that a task has settled only pass by
            yield b.filter(settled)
            b = b.filter(pc.invert(settled))
            for k, d, p, h in zip(*(b.column(c).to_pylist() for c in range(4))):
                if k != bucket and sent:
                    settle()
                    if sum(len(f[0]) for f in found) >= _FLUSH:
                        yield told()
                bucket = k
                sent.append((_unpack(d), _unpack(p), np.frombuffer(h, np.uint64)))
        if sent:
            settle()
        if found:
            yield told()

    return rows.mapInArrow(hashed, PACKED).repartition("bucket").sortWithinPartitions("bucket").mapInArrow(recurring, PACKED)


def _told(kind: int, to: np.ndarray, *columns: np.ndarray | None) -> pa.RecordBatch:
    """Rows of TOLD by bucket; columns are packed numbers, the last one bytes as they are."""
    order = np.argsort(to, kind="stable")
    cuts = _groups(to[order])
    parts = list(zip(cuts, np.concatenate((cuts[1:], [len(to)]))))
    packed = [pa.nulls(len(cuts), pa.binary()) if x is None else pa.array([_pack(x[order][s:e]) for s, e in parts], type=pa.binary()) for x in columns]
    return pa.RecordBatch.from_arrays([pa.array(to[order][cuts].astype(np.int32)), pa.array(np.full(len(cuts), kind, np.int32)), *packed, pa.nulls(len(cuts), pa.binary())], names=[f.split()[0] for f in TOLD.split(", ")])


def _merged(docs: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ranges of each document, those that touch joined."""
    order = np.lexsort((start, docs))
    docs, start, end = docs[order], start[order], end[order]
    new = np.zeros(len(docs), dtype=np.int64)
    new[_groups(docs)] = 1
    lift = np.cumsum(new) * (int(end.max(initial=0)) + 1)  # documents apart, so that one running maximum serves all
    reach = np.maximum.accumulate(end + lift)
    fresh = np.concatenate(([True], (start + lift)[1:] > reach[:-1]))
    cuts = np.flatnonzero(fresh)
    return docs[cuts], start[cuts], np.maximum.reduceat(end, cuts)


def _segments(proposed: DataFrame, size: int, shards: int) -> DataFrame:
    """TOLD rows: segments by the document's shard, and requests for the owners' words by the owner's shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        shard = None

        def settle():
            docs, at, firsts, delta = (np.concatenate(x) for x in zip(*held))
            held.clear()
            order = np.lexsort((at, delta, firsts, docs))
            docs, at, firsts, delta = (x[order] for x in (docs, at, firsts, delta))
            cuts = _groups(docs, firsts, delta, at - np.arange(len(at)))
            ends = np.concatenate((cuts[1:], [len(at)])) - 1
            until = at[ends] + size
            docs, at, firsts, delta = (x[cuts] for x in (docs, at, firsts, delta))
            yield _told(_SEGMENT, np.full(len(docs), shard), docs, at, until, firsts, delta)
            other = firsts != docs
            if other.any():
                owner, start, end = _merged(firsts[other], (at + delta)[other], (until + delta)[other])
                yield _told(_REQUEST, _shard_of(owner, shards), owner, start, end, np.full(len(owner), shard), None)

        for b in batches:
            for k, *packed in zip(*(b.column(c).to_pylist() for c in (0, 1, 2, 4, 5))):
                if k != shard and held:
                    yield from settle()
                shard = k
                held.append(tuple(map(_unpack, packed)))
        if held:
            yield from settle()

    return proposed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, TOLD)


OUT = "id long, n_words long, n_removed long, kept string, spans array<struct<at:int,until:int>>"
_SYMBOLS = "".join(map(chr, range(64, 96)))


class Codes:
    """Words as strings of equal length over 32 symbols; words outside the vocabulary share one of another symbol."""

    def __init__(self, vocabulary: set[bytes]):
        self.width = max(1, -(-max(1, len(vocabulary) - 1).bit_length() // 5))
        code = lambda n: "".join(_SYMBOLS[n >> 5 * k & 31] for k in range(self.width))
        self.of = {w: code(n) for n, w in enumerate(sorted(vocabulary))}
        self.other = "~" * self.width

    def __call__(self, words: list[bytes]) -> str:
        get, other = self.of.get, self.other
        return "".join([get(w, other) for w in words])


def _covered(words: int, spans: list[tuple[int, int]]) -> np.ndarray:
    step = np.zeros(words + 1, dtype=np.int32)
    at = np.asarray(spans, dtype=np.int64)
    np.add.at(step, at[:, 0], 1)
    np.add.at(step, at[:, 1], -1)
    return np.cumsum(step[:-1]) > 0


def _rows_of(packed: pa.Table) -> tuple[pa.Array, pa.Array]:
    """Ids and texts of a shard."""
    streams = [pa.ipc.open_stream(x.as_buffer()).read_all() for c in packed.column("rows").chunks for x in c]
    if not streams:
        return pa.array([], pa.int64()), pa.array([], pa.large_binary())
    rows = pa.concat_tables(streams).combine_chunks()
    return rows.column(0).chunk(0), rows.column(1).chunk(0).cast(pa.large_binary())


def _places(ids: pa.Array) -> dict[int, list[int]]:
    out: dict[int, list[int]] = {}
    for n, i in enumerate(ids.to_pylist()):
        if i is not None:
            out.setdefault(i, []).append(n)
    return out


class Owned:
    """The words that owners have at the places asked for; rows that share an id are variants of one owner."""

    def __init__(self, told: list[tuple]):
        self.of: dict[int, list[tuple[int, int, list[bytes]]]] = {}
        for docs, at, until, words in told:
            for d, s, e, w in zip(_unpack(docs).tolist(), _unpack(at).tolist(), _unpack(until).tolist(), zstandard.decompress(words).split(b"\n")):
                self.of.setdefault(d, []).append((s, e, w.split(b" ")))

    def has(self, owner: int, at: int, words: list[bytes]) -> bool:
        return any(s <= at and at + len(words) <= e and held[at - s : at - s + len(words)] == words for s, e, held in self.of.get(owner, ()))


def confirmed(doc: int, variants: list[list[bytes]], segments: list[tuple[int, int, int, int]], owned: Owned, size: int) -> Iterator[tuple[tuple[bytes, ...], int]]:
    """(passage, owner) of the rows of a document: runs of windows that smaller documents have, of which owner is the largest.

    segments are (first word, end, owner, delta); one that isn't equal in whole is tried window by window. One whose owner is the document itself
    leads to an earlier place of the same words, and is confirmed as far as that is.
    """
    none = np.iinfo(np.int64).min
    by = [np.full(max(0, len(w) - size + 1), none) for w in variants]
    for words, owners in zip(variants, by):
        for start, end, owner, delta in segments:
            if owner == doc:
                continue
            if end <= len(words) and owned.has(owner, start + delta, words[start:end]):
                owners[start : end - size + 1] = owner
                continue
            for a in range(start, min(end, len(words)) - size + 1):
                if owned.has(owner, a + delta, words[a : a + size]):
                    owners[a] = owner
    for words, owners in zip(variants, by):
        for start, end, owner, delta in segments:
            for a in range(start, min(end, len(words)) - size + 1) if owner == doc else ():
                for other, theirs in zip(variants, by):
                    if a + delta < len(theirs) and theirs[a + delta] != none and other[a + delta : a + delta + size] == words[a : a + size]:
                        owners[a] = max(owners[a], theirs[a + delta])
                        break
    for words, owners in zip(variants, by):
        at = np.flatnonzero(owners != none)
        for run in np.split(at, np.flatnonzero(np.diff(at) > 1) + 1) if len(at) else ():
            yield tuple(words[run[0] : run[-1] + size]), int(owners[run].max())


def dedup_substrings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window_words: int = 13, shards: int | None = None) -> DataFrame:
    """(id, n_words, n_removed, kept, spans): kept is the words that stay, joined by a blank; spans are the removed words' places.

    Of each window the words stay in the document with the smallest id that starts it. shards: unless given, one for each 64 MiB of
    text, and no fewer than four for each shuffle partition.
    """
    size = window_words
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t"))
    shards = shards or max(4 * shuffle_partitions(docs.sparkSession), (rows.agg(F.sum(F.octet_length("t"))).first()[0] or 0) // _SHARD)

    def shard(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of a shard as one compressed Arrow stream."""
        for b in batches:
            ids = b.column(0)
            to = _shard_of(ids.fill_null(0).to_numpy(zero_copy_only=False), shards)
            lost = np.flatnonzero(ids.is_null().to_numpy(zero_copy_only=False))
            to[lost] = lost % shards
            order = np.argsort(_small(to), kind="stable")
            cuts = np.flatnonzero(np.concatenate(([True], np.diff(to[order]) != 0))) if len(to) else []
            for part in np.split(order, cuts[1:]) if len(to) else []:
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, b.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
                    w.write_batch(b.take(pa.array(part)))
                yield pa.RecordBatch.from_arrays([pa.array([to[part[0]]], type=pa.int32()), pa.array([sink.getvalue().to_pybytes()], type=pa.binary())], names=["bucket", "rows"])

    def cut(key: tuple, packed: pa.Table, asked: pa.Table) -> pa.Table:
        """The words of owners at the places that other shards ask for, by the asking shard."""
        out = []
        if asked.num_rows:
            ids, texts = _rows_of(packed)
            at = _places(ids)
            want: dict[int, list[tuple[int, int, int]]] = {}
            for d, s, e, t in zip(*(asked.column(c).to_pylist() for c in ("docs", "at", "until", "firsts"))):
                for owner, *rest in zip(*(_unpack(x).tolist() for x in (d, s, e, t))):
                    want.setdefault(owner, []).append(tuple(rest))
            sent: dict[int, list[tuple[int, int, int, bytes]]] = {}
            for owner, ranges in sorted(want.items()):
                for n in at.get(owner, ()):
                    words = (texts[n].as_py() or b"").split()
                    for s, e, to in ranges:
                        sent.setdefault(to, []).append((owner, s, min(e, len(words)), b" ".join(words[s:e])))
            for to, told in sent.items():
                d, s, e, w = zip(*told)
                out.append((to, _PHRASE, _pack(d), _pack(s), _pack(e), None, None, zstandard.compress(b"\n".join(w), 1)))
        kinds = (pa.int32(), pa.int32(), *[pa.binary()] * 6)
        return pa.Table.from_arrays([pa.array([r[c] for r in out], type=k) for c, k in enumerate(kinds)], names=[f.split()[0] for f in TOLD.split(", ")])

    def locate(key: tuple, packed: pa.Table, told: pa.Table) -> pa.Table:
        ids, texts = _rows_of(packed)
        by_kind: dict[int, list[tuple]] = {_SEGMENT: [], _PHRASE: []}
        for row in zip(*(told.column(c).to_pylist() for c in ("kind", "docs", "at", "until", "firsts", "delta", "words"))):
            by_kind[row[0]].append(row[1:])
        owned = Owned([(d, s, e, w) for d, s, e, _, _, w in by_kind[_PHRASE]])
        segments: dict[int, list[tuple[int, int, int, int]]] = {}
        for d, s, e, f, x, _ in by_kind[_SEGMENT]:
            for doc, *rest in zip(*(_unpack(v).tolist() for v in (d, s, e, f, x))):
                segments.setdefault(doc, []).append(tuple(rest))
        words_of = lambda n: (texts[n].as_py() or b"").split()
        phrases: dict[tuple[bytes, ...], int] = {}
        for doc, at in _places(ids).items() if segments else ():
            if doc in segments:
                for phrase, owner in confirmed(doc, [words_of(n) for n in at], segments[doc], owned, size):
                    phrases[phrase] = min(owner, phrases.get(phrase, owner))
        code = Codes({w for p in phrases for w in p})
        automaton = ahocorasick.Automaton()
        for phrase, owner in phrases.items():
            automaton.add_word(code(phrase), (len(phrase), owner))
        if phrases:
            automaton.make_automaton()
        out, width = [], code.width
        for n, i in enumerate(ids.to_pylist()):
            words, hits = words_of(n), []
            if phrases and i is not None and len(words) >= size:
                for end, (count, owner) in automaton.iter(code(words)):
                    if owner < i and (end + 1) % width == 0:
                        hits.append(((end + 1) // width - count, (end + 1) // width))
            if hits:
                gone = _covered(len(words), hits)
                edge = np.flatnonzero(np.diff(np.concatenate(([0], gone.view(np.int8), [0]))))
                kept = [w for w, g in zip(words, gone.tolist()) if not g]
                spans = [{"at": int(s), "until": int(e)} for s, e in edge.reshape(-1, 2)]
            else:
                kept, spans = words, []
            out.append((len(words), len(words) - len(kept), b" ".join(kept).decode(), spans))
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("at", pa.int32()), ("until", pa.int32())])))
        return pa.Table.from_arrays([ids, *(pa.array([r[c] for r in out], type=k) for c, k in enumerate(kinds))], names=["id", "n_words", "n_removed", "kept", "spans"])

    dealt = rows.mapInArrow(shard, "bucket int, rows binary")
    told = checkpointed(_segments(_propose(rows, size, shards), size, shards))
    phrases = dealt.groupBy("bucket").cogroup(told.where(F.col("kind") == _REQUEST).groupBy("bucket")).applyInArrow(cut, TOLD)
    both = told.where(F.col("kind") == _SEGMENT).union(phrases)
    return dealt.groupBy("bucket").cogroup(both.groupBy("bucket")).applyInArrow(locate, OUT)


def op4(docs: DataFrame) -> DataFrame:
    out = dedup_substrings(docs)
    return out.select(F.col("id").alias("doc_id"), "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))

"""SentencePiece encoding and decoding by a shared-prefix forward pass.

A text becomes a blank mark, then the text with blanks as marks; it is cut before each run of marks, and no piece
crosses a cut. The distinct marked words of a batch are sorted, which is the depth-first order of their trie, and each word
starts from the forward states it shares with the word before.

The model given is a BPE model: the path with the largest sum of its scores isn't what the model's own library yields, so the
forward pass keeps, for each prefix, the one last piece of the prefix's BPE encoding (a piece may follow another only if merging in
rank order would leave their border alone) instead of the best sum. That is exact, and the state of a prefix is still all that a longer word needs.

Defined results: null gives null; an empty text no ids; characters without a piece become byte pieces; decoding turns marks
into blanks and drops the first, so a text comes back exactly unless it holds the mark itself (U+2581), which reads as a blank; ids outside
the vocabulary are an error. All columns of a row pass through; one named like the result is replaced.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import released

MARK = "▁"
MAX_MODEL_BYTES = 64 << 20
TAIL = 4
SLICE_BYTES = 1 << 20


def default_model_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class PieceModel:
    """Pieces, their merge ranks and how each came about; small enough to broadcast."""

    def __init__(self, path: str):
        import sentencepiece as sp

        with open(path, "rb") as f:
            proto = f.read(MAX_MODEL_BYTES + 1)
        if len(proto) > MAX_MODEL_BYTES:
            raise ValueError("the model is too large to broadcast")
        p = sp.SentencePieceProcessor(model_proto=proto)
        special = lambda i: p.is_control(i) or p.is_unknown(i) or p.is_byte(i) or p.is_unused(i)
        pieces = [(p.id_to_piece(i), i, p.get_score(i)) for i in range(p.get_piece_size()) if not special(i)]
        self.byte_ids = [p.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.raw = [b"" if p.is_control(i) else p.id_to_piece(i).replace(MARK, " ").encode() for i in range(p.get_piece_size())]
        for b, i in enumerate(self.byte_ids):
            self.raw[i] = bytes([b])
        self.rank, self.ids = {}, {}
        for r, (s, i, _) in enumerate(sorted(pieces, key=lambda x: (-x[2], x[1])), 1):
            self.ids[s] = i
            if len(s) > 1 and s.strip(MARK):
                self.rank[s] = r
        self.runs = {s for s in self.ids if not s.strip(MARK)}
        self.parts = {}
        for s in sorted(self.rank, key=self.rank.get):
            split = self._last_merge(s)
            if split:
                self.parts[s] = split
        self.known = {s: s for s in self.ids if s in self.parts or len(s) == 1}
        #: Lengths, longest first, of the pieces that end in the same few characters: no other length can end there.
        lengths: dict[str, set[int]] = {}
        for x in self.known:
            if len(x) >= TAIL:
                lengths.setdefault(x[-TAIL:], set()).add(len(x))
        self.short = tuple(range(TAIL - 1, 0, -1))
        self.tails = {x: (*sorted(n, reverse=True), *self.short) for x, n in lengths.items()}

    def _last_merge(self, s: str) -> tuple[str, str] | None:
        """The two pieces whose merge gives s, if merging the characters of s in rank order ends in s."""
        at = list(s)
        while len(at) > 2:
            ranks = [self.rank.get(a + b, 1 << 60) for a, b in zip(at, at[1:])]
            k = min(range(len(ranks)), key=ranks.__getitem__)
            if ranks[k] == 1 << 60:
                return None
            at[k : k + 2] = [at[k] + at[k + 1]]
        return (at[0], at[1]) if len(at) == 2 else None

    def stay_apart(self, a: str, b: str) -> bool:
        """Whether BPE leaves the border between pieces a and b; later merges are undone first, the right one of equals."""
        before = 1 << 60
        rank = self.rank
        while True:
            if rank.get(a + b, 1 << 60) < before:
                return False
            x, y = rank.get(a, 0), rank.get(b, 0)
            if x > y:
                before, a = x, self.parts[a][1]
            elif y:
                before, b = y + 1, self.parts[b][0]
            else:
                return True

    def mark_run(self, n: int) -> list[int]:
        """Ids of n marks: equal scores, so the leftmost pair that is a piece merges first."""
        at = [MARK] * n
        while True:
            k = next((k for k in range(len(at) - 1) if at[k] + at[k + 1] in self.runs), None)
            if k is None:
                return [self.ids[x] for x in at]
            at[k : k + 2] = [at[k] + at[k + 1]]


def gather(starts: np.ndarray, sizes: np.ndarray, flat: np.ndarray) -> np.ndarray:
    """The concatenation of flat[starts[k] : starts[k] + sizes[k]] over all k."""
    ends = np.cumsum(sizes, dtype=np.int64)
    total = int(ends[-1]) if len(ends) else 0
    return flat[np.repeat(starts - (ends - sizes), sizes) + np.arange(total, dtype=np.int64)]


class Encoder:
    """Encodes batches of texts; what it has learned of word pairs and words stays bounded.

    A word is known by what follows its one mark; a word behind several marks, or a run of them, by all of it, marks included.
    """

    CUT = re.compile(f"{MARK}+[^{MARK}]*")

    def __init__(self, model: PieceModel, max_known: int = 400_000):
        self.m, self.max_known, self.apart = model, max_known, {}
        self._forget()

    def _forget(self) -> None:
        self.at, self.flat, self.starts = {}, array("i"), array("q", [0])

    def _remember(self, word: str, ids: list[int]) -> None:
        self.at[word] = len(self.at)
        self.flat.extend(ids)
        self.starts.append(len(self.flat))

    def _ids(self, word: str) -> list[int]:
        k = self.at[word]
        return self.flat[self.starts[k] : self.starts[k + 1]].tolist()

    def learn(self, new: set[str]) -> None:
        """Encodes words of one mark: sorted, each begins with the forward states that it shares with the one before."""
        m, apart = self.m, self.apart
        get, tails, short = m.known.get, m.tails.get, m.short
        last, back, before = [None], [0], ""
        for bare in sorted(new):
            word = MARK + bare
            n, k = min(len(word), len(before)), 0
            while k < n and word[k] == before[k]:
                k += 1
            del last[k + 1 :], back[k + 1 :]
            for i in range(k + 1, len(word) + 1):
                for n in tails(word[i - TAIL : i], short) if i >= TAIL else short:
                    s = i - n
                    if s < 0 or (piece := get(word[s:i])) is None:
                        continue
                    left = last[s]
                    if left is not None:
                        ok = apart.get((left, piece))
                        if ok is None:
                            ok = apart[left, piece] = m.stay_apart(left, piece)
                        if not ok:
                            continue
                    last.append(piece)
                    back.append(s)
                    break
                else:
                    last.append(None)  # no piece: bytes, which never merge
                    back.append(i - 1)
            ids, i = [], len(word)
            while i:
                piece = last[i]
                ids.extend([m.byte_ids[b] for b in reversed(word[i - 1].encode())] if piece is None else (m.ids[piece],))
                i = back[i]
            ids.reverse()
            self._remember(bare, ids)
            before = word
        if len(apart) > self.max_known:
            apart.clear()

    def _learn_runs(self, runs: set[str]) -> None:
        """A run of marks is encoded apart from the word behind it, which takes the last mark if a piece of it begins so."""
        for w in runs:
            bare = w.lstrip(MARK)
            n = len(w) - len(bare)
            if not bare:
                self._remember(w, self.m.mark_run(n))
                continue
            ids = self._ids(bare)
            alone = ids[0] == self.m.ids[MARK]
            self._remember(w, self.m.mark_run(n if alone else n - 1) + (ids[1:] if alone else ids))

    def _cut(self, text: str | None) -> list[str]:
        if not text:
            return []
        text = text.replace(MARK, " ")
        words = text.split(" ")
        if "" not in words:  # one mark before each word
            return words
        return [w if w[1:2] in ("", MARK) else w[1:] for w in self.CUT.findall(MARK + text.replace(" ", MARK))]

    def encode(self, texts: list[str | None]) -> pa.ListArray:
        """A list of ids for each text."""
        if len(self.at) > self.max_known:
            self._forget()
        cut = [self._cut(t) for t in texts]
        words = list(chain.from_iterable(cut))
        new = set(words).difference(self.at)
        runs = {w for w in new if w[0] == MARK}
        self.learn((new - runs) | {b for w in runs if (b := w.lstrip(MARK)) and b not in self.at})
        self._learn_runs(runs)
        index = np.fromiter(map(self.at.__getitem__, words), dtype=np.int64, count=len(words))
        starts = np.array(self.starts, dtype=np.int64)
        sizes = np.diff(starts)[index]
        ids = gather(starts[index], sizes, np.array(self.flat, dtype=np.int32))
        ends = np.concatenate(([0], np.cumsum(sizes)))[np.concatenate(([0], np.cumsum([len(c) for c in cut], dtype=np.int64)))]
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(ids), mask=pa.array([t is None for t in texts], pa.bool_()))


class Decoder:
    """Texts of lists of ids: the bytes of all pieces in one array, gathered by piece."""

    def __init__(self, model: PieceModel):
        self.sizes = np.array([len(x) for x in model.raw], dtype=np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.flat = np.frombuffer(b"".join(model.raw), dtype=np.uint8)

    def decode(self, lists: pa.ListArray) -> pa.Array:
        ids = lists.flatten().to_numpy(zero_copy_only=False)
        if len(ids) and not (0 <= ids.min() and ids.max() < len(self.sizes)):
            raise IndexError("an id outside the vocabulary")
        counts = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        sizes = self.sizes[ids]
        data = gather(self.starts[ids], sizes, self.flat)
        of = np.concatenate(([0], np.cumsum(sizes)))[np.concatenate(([0], np.cumsum(counts, dtype=np.int64)))]
        first, end = of[:-1], of[1:]
        keep = np.ones(len(data), dtype=bool)
        keep[first[end > first]] = False  # the blank of the first mark
        offsets = of - np.concatenate(([0], np.cumsum(end > first)))
        nulls = lists.is_null().to_numpy(zero_copy_only=False)
        valid = pa.py_buffer(np.packbits(~nulls, bitorder="little"))
        raw = pa.Array.from_buffers(pa.binary(), len(lists), [valid, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(data[keep])])
        try:
            return raw.cast(pa.string())
        except pa.ArrowInvalid:  # bytes that are no UTF-8, from ids that no text gave
            return pa.array([None if x is None else x.decode("utf-8", "replace") for x in raw.to_pylist()], pa.string())


def _pieces_of_batches(batches, column: int, most: int):
    """Slices of a batch with about `most` bytes in one column."""
    for b in batches:
        at = 0
        step = max(1, int(b.num_rows * most / max(most, b.column(column).nbytes)))
        while at < b.num_rows:
            yield b.slice(at, step)
            at += step


def _with(schema: T.StructType, name: str, kind: T.DataType) -> T.StructType:
    return T.StructType([f for f in schema.fields if f.name != name] + [T.StructField(name, kind)])


def encode(docs: DataFrame, text_col: str = "text", out_col: str = "ids", model_path: str | None = None) -> DataFrame:
    """docs with an array of piece ids for text_col."""
    model = docs.sparkSession.sparkContext.broadcast(PieceModel(model_path or default_model_path()))
    names = [c for c in docs.columns if c != out_col]
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = Encoder(model.value)
        for b in _pieces_of_batches(batches, at, SLICE_BYTES):
            ids = coder.encode(b.column(at).to_pylist())
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), ids], names=[*names, out_col])

    return docs.mapInArrow(released(run), _with(docs.schema, out_col, T.ArrayType(T.IntegerType())))


def decode(docs: DataFrame, ids_col: str = "ids", out_col: str = "text", model_path: str | None = None) -> DataFrame:
    """docs with the text of the piece ids in ids_col."""
    model = docs.sparkSession.sparkContext.broadcast(PieceModel(model_path or default_model_path()))
    names = [c for c in docs.columns if c != out_col]
    at = docs.columns.index(ids_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = Decoder(model.value)
        for b in _pieces_of_batches(batches, at, SLICE_BYTES):
            out = decoder.decode(b.column(at))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), out], names=[*names, out_col])

    return docs.mapInArrow(released(run), _with(docs.schema, out_col, T.StringType()))


def op5(docs: DataFrame) -> DataFrame:
    """(doc_id, ids, n_ids, decoded_sha256, round_trip): round_trip compares the decoded text with the given one."""
    from pyspark.sql import functions as F

    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("given", F.sha2("text", 256))
    back = decode(encode(rows, out_col="text").withColumnRenamed("text", "ids"))  # ids take the texts' place: they needn't travel on
    sha = F.sha2("text", 256)
    return back.select("doc_id", "ids", F.size("ids").cast("long").alias("n_ids"), sha.alias("decoded_sha256"), (sha == F.col("given")).alias("round_trip"))

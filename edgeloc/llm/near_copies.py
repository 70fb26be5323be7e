"""SimHash near copies at a similarity: texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more.

The method is the SimHash query's, tiles compared with exclusive-or and bit counts, with parameters of its own: at a similarity of 0.8 two 64-bit
fingerprints differ in 10 bits on average, so the radius is 24 (five deviations above), and each pair within it is verified by its exact
similarity. Blocks of bits that must agree at such a radius would hold next to nothing, so min-hash bands cut the groups in which tiles are
compared: 40 bands of 8 hashes, of which a pair at 0.8 shares none with a probability of 6e-4, at 0.85 of 7e-6. Texts joined by bands form loose groups. Each loose
group's texts meet in one task, or, above `tile_rows` texts, in one task for each pair of its tiles. A task emits a forest.

Defined results: words are those of the SimHash query (ASCII blanks, A-Z lowered); a text of fewer than five words is one shingle, null and texts without
words are alike; equal shingle sets, known by a 64-bit hash, are one node; groups are transitive.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, released, text_key
from .components import connected_components

BANDS, ROWS = 40, 8
RADIUS, SMALL = 24, 32
_RNG = np.random.default_rng(42)
_XOR = _RNG.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)
_MUL = _RNG.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32) | np.uint32(1)


def shingle_set(text: bytes | None, shingle_words: int = 5, seed: int = 42) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(1, dtype=np.uint64)
    joined, n = b" ".join(words), max(1, len(words) - shingle_words + 1)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[:n].tolist()
    ends = ends[min(shingle_words, len(words)) - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(joined[s:e], seed) for s, e in zip(starts, ends)], dtype=np.uint64))


def set_fingerprint(shingles: np.ndarray) -> int:
    """A bit is 1 if set in over half of the distinct shingles' hashes."""
    counts = np.zeros(64, dtype=np.int64)
    for at in range(0, len(shingles), 1 << 16):
        counts += np.unpackbits(shingles[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(shingles), bitorder="little").view("<u8")[0])


def node_of(shingles: np.ndarray) -> int:
    return int(np.array(xxhash.xxh64_intdigest(shingles.tobytes()), dtype=np.uint64).view(np.int64))


def band_keys(shingles: np.ndarray, chunk: int = 512) -> np.ndarray:
    """A hash of each band's min-hashes."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    least = np.full(BANDS * ROWS, 0xFFFFFFFF, dtype=np.uint32)
    for at in range(0, len(x), chunk):
        np.minimum(least, ((x[at : at + chunk, None] ^ _XOR) * _MUL).min(0), out=least)
    said = least.reshape(BANDS, ROWS)
    return np.array([xxhash.xxh64_intdigest(row.tobytes(), k) for k, row in enumerate(said)], dtype=np.uint64).view(np.int64)


def _signed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                sets = [shingle_set(t) for t in part.column(1).cast(pa.binary()).to_pylist()]
                keys = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * BANDS), pa.array(np.concatenate([band_keys(s) for s in sets])))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), pa.array([node_of(s) for s in sets], type=pa.int64()), keys], names=["id", "k1", "k2", "node", "keys"])

    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), text.alias("t"), *(k.alias(n) for k, n in zip(text_key(F.coalesce(text, F.lit(""))), ("k1", "k2"))))
    return rows.mapInArrow(released(run), "id long, k1 long, k2 long, node long, keys array<long>")


def similar_links(sets: list[np.ndarray], radius: int = RADIUS, tile: int = 512) -> list[tuple[int, int]]:
    """A forest whose components are those of all pairs with a similarity of 0.8 or more whose fingerprints differ in at most radius bits.

    Tiles of fingerprints, sorted by population count, are compared with exclusive-or and bit counts; tile pairs whose counts differ by more than
    radius are skipped. Sets below SMALL shingles are in tiles of their own, compared whatever their bits: so few shingles say little in 64 bits.
    """
    fps = np.array([set_fingerprint(x) for x in sets], dtype=np.uint64)
    sizes = np.array([len(x) for x in sets], dtype=np.int64)
    pops = np.bitwise_count(fps).astype(np.int16)
    root, out = np.arange(len(sets)), []

    def compare(i: int, others: np.ndarray) -> None:
        if not len(others):
            return
        low, high = np.minimum(sizes[i], sizes[others]), np.maximum(sizes[i], sizes[others])
        for j in others[5 * low >= 4 * high].tolist():
            if root[i] != root[j]:
                both = np.intersect1d(sets[i], sets[j], assume_unique=True).size
                if 9 * both >= 4 * (sizes[i] + sizes[j]):
                    root[root == root[j]] = root[i]
                    out.append((i, j))

    order = np.lexsort((np.arange(len(sets)), pops))
    for a in range(0, len(order), tile):
        mine = order[a : a + tile]
        for b in range(a, len(order), tile):
            theirs = order[b : b + tile]
            if pops[theirs[0]] - pops[mine[-1]] > radius:
                break
            near = np.bitwise_count(fps[mine, None] ^ fps[None, theirs]) <= radius
            if a == b:
                near &= np.tri(len(mine), k=-1, dtype=bool)
            for x in np.flatnonzero(near.any(1)).tolist():
                others = theirs[near[x]]
                compare(int(mine[x]), others[root[others] != root[mine[x]]])
    small = np.flatnonzero(sizes < SMALL)
    small = small[np.argsort(sizes[small], kind="stable")]
    for k, i in enumerate(small.tolist()):
        reach = int(np.searchsorted(4 * sizes[small], 5 * sizes[i], side="right"))
        others = small[k + 1 : reach]
        compare(i, others[root[others] != root[i]])
    return out


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tile_rows: int = 512) -> DataFrame:
    """(id, k1, k2, component, label): one row for each row of docs; component is the smallest id reachable over similar texts.

    k1 and k2 tell the row's text, by common.text_key, and label its group: where rows share an id, two groups may have the same smallest one.
    """
    rows = checkpointed(_signed(docs, id_col, text_col))
    nodes = rows.groupBy("node").agg(F.min("id").alias("least"), F.first("keys").alias("keys"))
    keyed = nodes.select("node", F.explode("keys").alias("key"))
    shared = keyed.groupBy("key").agg(F.min("node").alias("a"), F.max("node").alias("z")).where("a < z").select("key", "a")
    loose = checkpointed(connected_components(keyed.join(shared, "key").select("a", F.col("node").alias("b")).where("a <> b")))

    tiles = loose.groupBy("label").agg(F.ceil(F.count("*") / tile_rows).cast("int").alias("tiles"))
    own = F.pmod(F.xxhash64("node"), F.col("tiles")).cast("int")
    jobs = F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), lambda t: F.xxhash64("label", F.least(own, t), F.greatest(own, t)))
    dealt = loose.join(tiles, "label").join(nodes.select("node", "least"), "node").select(F.col("least").alias("id"), "node", jobs.alias("jobs"))
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t"))
    dealt = dealt.join(texts, "id").select(F.explode("jobs").alias("job"), "node", "t").repartition("job").sortWithinPartitions("job")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        job, sets = None, {}

        def links():
            names = list(sets)
            found = similar_links([sets[k] for k in names]) if len(names) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([names[x[n]] for x in found], type=pa.int64()) for n in (0, 1)], names=["a", "b"])

        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                for j, node, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2).cast(pa.binary()).to_pylist()):
                    if j != job:
                        yield links()
                        job, sets = j, {}
                    if node not in sets and node_of(found := shingle_set(t)) == node:  # rows that share an id may have other texts
                        sets[node] = found
        yield links()

    labels = connected_components(dealt.mapInArrow(released(run), "a long, b long"))
    placed = nodes.select("node", "least").join(labels, "node", "left").select("node", "least", F.coalesce("label", "node").alias("label"))
    named = placed.join(placed.groupBy("label").agg(F.min("least").alias("component")), "label").select("node", "component", "label")
    return rows.select("id", "k1", "k2", "node").join(named, "node").select("id", "k1", "k2", "component", "label")

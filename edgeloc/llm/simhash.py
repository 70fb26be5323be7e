"""SimHash near-duplicates: 64-bit fingerprints compared exactly, tile by tile, in numpy.

Two fingerprints within `radius` bits agree on at least blocks - radius of `blocks` bit blocks, so tiles
are cut inside groups that agree on such a choice of blocks. No pair within the radius is lost. A tile is
sorted by population count; tile pairs whose counts differ by more than the radius are skipped, the others are
compared with exclusive-or and bit counts. Groups above `tile_rows` fingerprints are dealt to several tasks, one for each pair of their
tiles. A task emits links that form a forest, never all pairs.

Defined results: null text counts as empty; texts without words get fingerprint zero and link like any other;
a null id gets a fingerprint and a component, but never names one (a component of null ids only is null); repeated rows stay repeated; an empty table gives an empty one.
Only the named id and text columns are read, so other columns can't clash.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed
from .components import connected_components


def fingerprint(text: bytes | None, shingle_words: int = 4, seed: int = 42) -> int:
    words = (text or b"").lower().split()  # of bytes: A-Z only, and the six ASCII blanks
    if not words:
        return 0
    joined, n = b" ".join(words), max(1, len(words) - shingle_words + 1)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[:n].tolist()
    ends = ends[min(shingle_words, len(words)) - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(joined[s:e], seed) for s, e in zip(starts, ends)], dtype="<u8")
    counts = np.zeros(64, dtype=np.int64)
    for at in range(0, n, 1 << 16):
        counts += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle_words: int = 4, seed: int = 42) -> DataFrame:
    """(id, fp): fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                fps = np.array([fingerprint(t, shingle_words, seed) for t in part.column(1).cast(pa.binary()).to_pylist()], dtype=np.uint64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fps.view(np.int64))], names=["id", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t"))
    return rows.mapInArrow(run, "id long, fp long")


def _merge(root: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Join the trees of i and j; root keeps each item's smallest tree member."""
    while True:
        a, b = root[i], root[j]
        differ = a != b
        if not differ.any():
            return root
        i, j, a, b = i[differ], j[differ], a[differ], b[differ]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = root[root]
            if np.array_equal(up, root):
                break
            root = up


def link_tiles(job: np.ndarray, fp: np.ndarray, radius: int, tile: int = 512, small: int = 48) -> np.ndarray:
    """For rows sorted by job and population count: the first row, in the same job, that each row is linked to."""
    n = len(fp)
    root, pops = np.arange(n), np.bitwise_count(fp).astype(np.int16)
    cuts = np.flatnonzero(np.concatenate(([True], job[1:] != job[:-1]))) if n else np.array([], dtype=int)
    sizes = np.diff(np.concatenate((cuts, [n])))
    left = np.repeat(np.where(sizes <= small, cuts + sizes, 0), sizes)  # end of a small job
    i, shift = np.flatnonzero(left), 1
    while len(i := i[i + shift < left[i]]):
        near = np.bitwise_count(fp[i] ^ fp[i + shift]) <= radius
        root = _merge(root, i[near], i[near] + shift)
        shift += 1
    for start, size in zip(cuts[sizes > small], sizes[sizes > small]):
        for a in range(start, start + size, tile):
            a_end = min(a + tile, start + size)
            for b in range(a, start + size, tile):
                if pops[b] - pops[a_end - 1] > radius:
                    break
                near = np.bitwise_count(fp[a:a_end, None] ^ fp[None, b : min(b + tile, start + size)]) <= radius
                x, y = np.nonzero(near)
                root = _merge(root, x + a, y + b)
    return root


def fingerprint_links(fps: DataFrame, radius: int = 4, blocks: int = 6, tile_rows: int = 4096) -> DataFrame:
    """Distinct fingerprints fps(fp) -> links (a, b) whose components are those of all pairs within the radius."""
    if not radius < blocks <= 64:
        raise ValueError("blocks must exceed radius")
    bounds = [round(k * 64 / blocks) for k in range(blocks + 1)]
    masks = [sum((1 << bounds[k + 1]) - (1 << bounds[k]) for k in kept) for kept in combinations(range(blocks), blocks - radius)]
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    keys = F.array(*(F.xxhash64(F.lit(c), F.col("fp").bitwiseAND(F.lit(m))) for c, m in enumerate(signed)))
    keyed = fps.select("fp", F.explode(keys).alias("key"))
    hot = keyed.groupBy("key").count().where(F.col("count") > tile_rows).select("key", F.ceil(F.col("count") / tile_rows).cast("int").alias("tiles"))
    own = F.pmod(F.xxhash64("fp"), F.col("tiles")).cast("int")
    jobs = F.when(F.col("tiles").isNull(), F.array("key")).otherwise(F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), lambda t: F.xxhash64("key", F.least(own, t), F.greatest(own, t))))
    dealt = keyed.join(hot, "key", "left").select("fp", F.explode(jobs).alias("job"))
    dealt = dealt.repartition("job").sortWithinPartitions("job", F.bit_count("fp"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        job, fp = np.array([], dtype=np.int64), np.array([], dtype=np.uint64)

        def links(job, fp):
            root = link_tiles(job, fp, radius)
            told = np.flatnonzero(root != np.arange(len(root)))
            return pa.RecordBatch.from_arrays([pa.array(fp[told].view(np.int64)), pa.array(fp[root[told]].view(np.int64))], names=["a", "b"])

        for b in batches:
            if b.num_rows:
                job = np.concatenate((job, b.column(1).to_numpy()))
                fp = np.concatenate((fp, b.column(0).to_numpy().view(np.uint64)))
                whole = np.searchsorted(job, job[-1])  # the last job may go on in the next batch
                yield links(job[:whole], fp[:whole])
                job, fp = job[whole:], fp[whole:]
        yield links(job, fp)

    return dealt.mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle_words: int = 4, radius: int = 4, blocks: int = 6, tile_rows: int = 4096) -> DataFrame:
    """(id, fp, component): one row for each row of docs; component is the smallest id reachable over links."""
    rows = checkpointed(fingerprints(docs, id_col, text_col, shingle_words))
    nodes = rows.groupBy("fp").agg(F.min("id").alias("least"))
    labels = connected_components(fingerprint_links(nodes.select("fp"), radius, blocks, tile_rows))
    placed = nodes.join(labels.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("label", "fp").alias("label"))
    least = placed.groupBy("label").agg(F.min("least").alias("component"))
    named = placed.join(least, "label").select("fp", "component")
    return rows.join(named, "fp").select("id", "fp", "component")


def op2(docs: DataFrame) -> DataFrame:
    out = near_duplicates(docs)
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))

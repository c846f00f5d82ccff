"""Exact substring deduplication over a sparse suffix array, sorted by a common-prefix-aware merge.

Every byte that lies in a `length`-byte string which also starts in a document with a smaller id is removed.
Four exchanges, none of whole suffixes:

1. Documents become compressed blocks. Each window of `length` bytes belongs to a content-defined anchor
   (anchors.py); a block sends one short record for each run of windows with one anchor.
2. Where all bytes of a run are the same in a smaller document, its bytes go. Of equal runs the one of the smallest
   document stands for the others; those whose anchor has other surroundings elsewhere are left to be compared.
3. Blocks sort the suffixes at these anchors, front-code them, and send each range of the order to its merger. A loser
   tree merges the runs and keeps the length of every prefix that it knows, so no known prefix is compared again;
   its output, a suffix array with common prefix lengths, tells which windows are equal.
4. Verdicts go back to their blocks, which cut the bytes.

What a task holds is a block, or a range of anchors, however often a passage is repeated.
"""

from __future__ import annotations

import hashlib
import struct
from bisect import bisect_right
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anchors import anchor_runs
from .common import discard, drawn, let_go, partitions, written

GRAM = 16
BLOCK_BYTES = 4_000_000
#: Suffixes that are looked at to place the borders of ranges, which only balance the mergers' work.
BORDER_SAMPLE = 4_000
BLOCKS = "block long, ids binary, sizes binary, data binary"
_U = np.uint64


def squeeze(*columns: np.ndarray | bytes) -> bytes:
    """Columns as planes of bytes, compressed together."""
    out = []
    for c in columns:
        if not isinstance(c, bytes):
            c = np.ascontiguousarray(c)
            c = c.view(np.uint8).reshape(len(c), -1).T.tobytes()
        out.append(c)
    head = struct.pack(f"<{len(out) + 1}I", len(out), *map(len, out))
    return zstandard.ZstdCompressor(level=1).compress(head + b"".join(out))


def expand(blob: bytes, *types: str | None) -> list:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    (n,) = struct.unpack_from("<I", raw)
    sizes, at, out = struct.unpack_from(f"<{n}I", raw, 4), 4 * (n + 1), []
    for size, kind in zip(sizes, types, strict=True):
        part = raw[at : at + size]
        at += size
        if kind is not None:
            width = np.dtype(kind).itemsize
            part = np.ascontiguousarray(np.frombuffer(part, np.uint8).reshape(width, -1).T).view(kind).reshape(-1)
        out.append(part)
    return out


def blocks(docs: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Documents, several to a row: ids, sizes in bytes, and their UTF-8 bytes compressed together. None is cut."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        number, ids, texts, size = TaskContext.get().partitionId() << 32, [], [], 0

        def row() -> pa.RecordBatch:
            data = zstandard.ZstdCompressor(level=3).compress(b"".join(texts))
            sizes = np.asarray([len(t) for t in texts], np.int64).tobytes()
            return pa.RecordBatch.from_pylist([{"block": number, "ids": np.asarray(ids, np.int64).tobytes(), "sizes": sizes, "data": data}])

        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                t = (text.as_py() or "").encode("utf-8", "surrogatepass")
                if ids and size + len(t) > block_bytes:
                    yield row()
                    number, ids, texts, size = number + 1, [], [], 0
                ids.append(doc)
                texts.append(t)
                size += len(t)
        if ids:
            yield row()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(made, BLOCKS)


def unpack(ids: bytes, sizes: bytes, data: bytes) -> tuple[np.ndarray, np.ndarray, bytes]:
    """Ids, where each document begins (and the end), and all bytes."""
    starts = np.concatenate(([0], np.cumsum(np.frombuffer(sizes, np.int64))))
    return np.frombuffer(ids, np.int64), starts, zstandard.ZstdDecompressor().decompress(data) if starts[-1] else b""


def _rows(batch: pa.RecordBatch | pa.Table) -> Iterator[tuple]:
    return zip(*[[x.as_py() for x in c] for c in batch.columns], strict=True)


def run_records(length: int, parts: int) -> Callable:
    """Of each block: for each part of the anchors' hashes, the runs of windows whose anchor falls there."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        for b in batches:
            for block, ids, sizes, data in _rows(b):
                doc_ids, starts, raw = unpack(ids, sizes, data)
                first, count, anchor, gram, cover = anchor_runs(np.frombuffer(raw, np.uint8), starts, length, GRAM)
                if not len(first):
                    continue
                part = ((gram >> _U(32)) * _U(parts) >> _U(32)).astype(np.int64)
                order = np.lexsort((gram & _U(2**32 - 1), part))
                cuts = np.searchsorted(part[order], np.arange(parts + 1))
                out = []
                for p in range(parts):
                    o = order[cuts[p] : cuts[p + 1]]
                    if len(o):
                        c = cover[o]
                        out.append({"part": p, "block": block, "blob": squeeze(
                            doc_ids, starts.astype(np.uint32), (gram[o] & _U(2**32 - 1)).astype(np.uint32), (c >> _U(32)).astype(np.uint32),
                            (c & _U(2**32 - 1)).astype(np.uint32), first[o].astype(np.uint32), count[o].astype(np.uint8), (anchor[o] - first[o]).astype(np.uint8))})
                yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("part", pa.int32()), ("block", pa.int64()), ("blob", pa.binary())]))

    return made


def _edges(*columns: np.ndarray) -> np.ndarray:
    """Where sorted rows begin to differ in any of the columns."""
    new = np.ones(len(columns[0]), dtype=bool)
    if len(new):
        new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    return new


VERDICTS = pa.schema([("block", pa.int64()), ("kind", pa.int32()), ("blob", pa.binary())])


def compare_runs(length: int) -> Callable:
    """Of one part: kind 0, runs whose bytes all go; kind 1, runs that are to be compared by window."""

    def made(table: pa.Table) -> pa.Table:
        let_go()
        cols, block_of = [], []
        names = table.column("block").to_pylist()
        for i, blob in enumerate(table.column("blob")):
            ids, starts, *rest = expand(blob.as_py(), "<i8", "<u4", "<u4", "<u4", "<u4", "<u4", "u1", "u1")
            doc = ids[np.searchsorted(starts, rest[3], side="right") - 1]
            cols.append([*rest, doc])
            block_of.append(np.full(len(doc), i, np.int32))
        gram, high, low, first, count, before, doc = (np.concatenate(x) for x in zip(*cols, strict=True))
        block = np.concatenate(block_of)
        cover = (high.astype(np.uint64) << _U(32)) | low
        order = np.lexsort((doc, cover, gram))
        gram, cover, doc, first, count, before, block = (x[order] for x in (gram, cover, doc, first, count, before, block))
        new_gram = _edges(gram)
        new_run = new_gram | _edges(cover)
        of_run, of_gram = np.cumsum(new_run) - 1, np.cumsum(new_gram) - 1
        smallest = doc[new_run][of_run]
        gone = doc > smallest
        at = np.flatnonzero(new_gram)
        several = (np.add.reduceat(new_run.astype(np.int32), at) > 1) & (np.minimum.reduceat(doc, at) != np.maximum.reduceat(doc, at))
        asked = ~gone & several[of_gram]
        out = []
        for kind, chosen in ((0, gone), (1, asked)):
            i = np.flatnonzero(chosen)
            i = i[np.argsort(block[i], kind="stable")]
            cuts = np.searchsorted(block[i], np.arange(len(names) + 1))
            for b, name in enumerate(names):
                o = i[cuts[b] : cuts[b + 1]]
                if len(o):
                    columns = (first[o], count[o]) if kind == 0 else (first[o], count[o], before[o])
                    out.append({"block": name, "kind": kind, "blob": squeeze(*columns)})
        return pa.Table.from_pylist(out, schema=VERDICTS)

    return made


def common_prefixes(strings: list[bytes]) -> np.ndarray:
    """Of sorted strings, the length of the prefix that each shares with the one before it."""
    out = np.zeros(len(strings), dtype=np.int64)
    if len(strings) > 1:
        sizes = np.asarray([len(s) for s in strings])
        width = int(sizes.max()) + 1
        grid = np.frombuffer(b"".join(s.ljust(width, b"\0") for s in strings), np.uint8).reshape(-1, width)
        differ = grid[1:] != grid[:-1]
        prefix = np.where(differ.any(axis=1), differ.argmax(axis=1), width)
        out[1:] = np.minimum(prefix, np.minimum(sizes[1:], sizes[:-1]))
    return out


def front_code(strings: list[bytes]) -> tuple[np.ndarray, np.ndarray, bytes]:
    """Sorted strings as shared prefix lengths, whole lengths, and what is left of each."""
    prefix = common_prefixes(strings)
    return prefix.astype(np.uint16), np.asarray([len(s) for s in strings], np.uint16), b"".join(s[p:] for s, p in zip(strings, prefix.tolist(), strict=True))


def front_decode(prefix: np.ndarray, sizes: np.ndarray, rest: bytes) -> list[bytes]:
    out, last, at = [], b"", 0
    for p, n in zip(prefix.tolist(), sizes.tolist(), strict=True):
        last = last[:p] + rest[at : at + n - p]
        at += n - p
        out.append(last)
    return out


def merge_runs(runs: list[tuple[list[bytes], list[int]]]) -> Iterator[tuple[int, int, int]]:
    """Merges sorted runs (strings, shared prefix lengths) by a loser tree: run, place in it, prefix shared with the last output.

    Each waiting string has the length of the prefix that it shares with the last winner it was compared with. The longer
    prefix wins without a look at the strings; only equal lengths are compared, from there on.
    """
    k = 1
    while k < len(runs):
        k *= 2
    place, known = [0] * k, [0] * k
    head: list[bytes | None] = [r[0][0] if r[0] else None for r in runs] + [None] * (k - len(runs))

    def beats(a: int, b: int) -> bool:
        """Whether a comes before b; whichever loses learns the prefix that both share."""
        x, y = head[a], head[b]
        if x is None or y is None:
            return y is None
        p, q = known[a], known[b]
        if p != q:
            return p > q
        end = min(len(x), len(y))
        while p < end and x[p] == y[p]:
            p += 1
        first = len(x) < len(y) or (len(x) == len(y) and a < b) if p == end else x[p] < y[p]
        known[b if first else a] = p
        return first

    losers = [0] * k
    winners = [0] * k + list(range(k))
    for node in range(k - 1, 0, -1):
        a, b = winners[2 * node], winners[2 * node + 1]
        if beats(a, b):
            winners[node], losers[node] = a, b
        else:
            winners[node], losers[node] = b, a
    top = winners[1] if k > 1 else 0
    while head[top] is not None:
        yield top, place[top], known[top]
        place[top] += 1
        strings, shared = runs[top]
        if place[top] < len(strings):
            head[top], known[top] = strings[place[top]], shared[place[top]]
        else:
            head[top] = None
        node = (top + k) // 2
        while node:
            if beats(losers[node], top):
                losers[node], top = top, losers[node]
            node //= 2


RUN = ("<u2", "<u2", None, "u1", None, "<i8", "<u4", "u1")


def sort_block(length: int) -> Callable:
    """Of a block and what is asked of it: the suffixes at the anchors, sorted and front-coded, with what stands before them."""

    def made(own: pa.Table, asked: pa.Table) -> pa.Table:
        let_go()
        schema = pa.schema([("block", pa.int64()), ("blob", pa.binary())])
        if not own.num_rows or not asked.num_rows:
            return schema.empty_table()
        block, ids, sizes, data = next(_rows(own))
        doc_ids, starts, raw = unpack(ids, sizes, data)
        first, count, before = (np.concatenate(x) for x in zip(*[expand(b.as_py(), "<u4", "u1", "u1") for b in asked.column("blob")], strict=True))
        first, count, before = first.astype(np.int64), count.astype(np.int64), before.astype(np.int64)
        doc = doc_ids[np.searchsorted(starts, first, side="right") - 1]
        cut = zip(first.tolist(), (first + before).tolist(), (first + count - 1 + length).tolist(), strict=True)
        left, right = [], []
        for a, b, c in cut:
            left.append(raw[a:b])
            right.append(raw[b:c])
        order = sorted(range(len(right)), key=lambda i: (right[i], left[i], int(doc[i]), int(first[i])))
        o = np.asarray(order)
        blob = squeeze(*front_code([right[i] for i in order]), before[o].astype(np.uint8), b"".join(left[i] for i in order), doc[o], first[o].astype(np.uint32), count[o].astype(np.uint8))
        return pa.Table.from_pylist([{"block": block, "blob": blob}], schema=schema)

    return made


def split_runs(borders: list[bytes]) -> Callable:
    """Sorted runs, cut at the borders; an anchor's suffixes stay together."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        for b in batches:
            for block, blob in _rows(b):
                prefix, sizes, rest, before, left, doc, first, count = expand(blob, *RUN)
                strings = front_decode(prefix, sizes, rest)
                ends = np.concatenate(([0], np.cumsum(before, dtype=np.int64)))
                part = np.asarray([bisect_right(borders, s[:GRAM]) for s in strings])
                cuts = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1], [True])))
                out = []
                for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                    own = squeeze(*front_code(strings[i:j]), before[i:j], left[ends[i] : ends[j]], doc[i:j], first[i:j], count[i:j])
                    out.append({"part": int(part[i]), "block": block, "blob": own})
                yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("part", pa.int32()), ("block", pa.int64()), ("blob", pa.binary())]))

    return made


def merge_part(length: int) -> Callable:
    """Of one range of suffixes: for each run of windows, as bits, those that also start in a smaller document (kind 2)."""

    def made(table: pa.Table) -> pa.Table:
        let_go()
        table = table.sort_by("block")
        names, runs, cols = table.column("block").to_pylist(), [], []
        for blob in table.column("blob"):
            prefix, sizes, rest, before, left, doc, first, count = expand(blob.as_py(), *RUN)
            runs.append((front_decode(prefix, sizes, rest), prefix.tolist()))
            grid = np.zeros((len(doc), length), np.uint8)  # row: the bytes before the anchor, the nearest first
            grid[np.arange(length)[None, :] < before[:, None]] = np.frombuffer(left, np.uint8)
            back = before[:, None].astype(np.int64) - 1 - np.arange(length)[None, :]
            grid = np.where(back >= 0, np.take_along_axis(grid, np.maximum(back, 0), axis=1), 0).astype(np.uint8)
            cols.append((doc, first, count, before, grid))
        base = np.concatenate(([0], np.cumsum([len(r[0]) for r in runs])))
        merged = np.fromiter((x for r, i, p in merge_runs(runs) for x in (base[r] + i, p)), np.int64, 2 * int(base[-1])).reshape(-1, 2)
        order, shared = merged[:, 0], merged[:, 1]
        doc, first, count, before, grid = (np.concatenate(x)[order] for x in zip(*cols, strict=True))
        run = np.searchsorted(base, order, side="right") - 1
        bits = np.zeros(len(doc), np.uint64)
        left_hash = np.full(len(doc), 7, np.uint64)
        for back in range(length):  # windows that begin so many bytes before the anchor
            have = np.flatnonzero((back <= before) & (back > before.astype(np.int64) - count))
            if len(have):
                group = np.cumsum(shared < length - back)[have]
                h, d = left_hash[have], doc[have]
                o = np.lexsort((d, h, group))
                new = _edges(group[o], h[o])
                smallest = d[o][new][np.cumsum(new) - 1]
                hit = have[o[d[o] > smallest]]
                bits[hit] |= _U(1) << (before[hit].astype(np.uint64) - _U(back))
            if back < length - 1:
                left_hash = (left_hash ^ (left_hash >> _U(29))) * _U(0x9E3779B97F4A7C15) + grid[:, back]
        out = []
        for r, name in enumerate(names):
            o = np.flatnonzero((run == r) & (bits > 0))
            if len(o):
                out.append({"block": name, "kind": 2, "blob": squeeze(first[o], bits[o])})
        return pa.Table.from_pylist(out, schema=VERDICTS)

    return made


def cut_block(length: int, with_text: bool) -> Callable:
    fields = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())]
    schema = pa.schema(fields + [("kept_text", pa.string())] * with_text)

    def made(own: pa.Table, verdicts: pa.Table) -> pa.Table:
        let_go()
        if not own.num_rows:
            return schema.empty_table()
        _, ids, sizes, data = next(_rows(own))
        doc_ids, starts, raw = unpack(ids, sizes, data)
        edge = np.zeros(len(raw) + 1, np.int32)
        for _, kind, blob in _rows(verdicts):
            if kind == 0:
                first, count = expand(blob, "<u4", "u1")
                at, end = first.astype(np.int64), first.astype(np.int64) + count + (length - 1)
            else:
                first, bits = expand(blob, "<u4", "<u8")
                rows, shifts = np.nonzero((bits[:, None] >> np.arange(64, dtype=np.uint64)[None, :]) & _U(1))
                at = first[rows].astype(np.int64) + shifts
                end = at + length
            np.add.at(edge, at, 1)
            np.subtract.at(edge, end, 1)
        gone = np.cumsum(edge[:-1]) > 0
        bytes_, columns = np.frombuffer(raw, np.uint8), [[] for _ in schema]
        for doc, a, b in zip(doc_ids.tolist(), starts[:-1].tolist(), starts[1:].tolist(), strict=True):
            mask = gone[a:b]
            n = int(mask.sum())
            kept = bytes_[a:b][~mask].tobytes() if n else raw[a:b]
            spans = int(mask[:1].sum() + (mask[1:] & ~mask[:-1]).sum()) if n else 0
            row = (doc, b - a, n, spans, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "ignore") if with_text else None)
            for c, x in zip(columns, row, strict=False):
                c.append(x)
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    return made


def remove_repeats(docs: DataFrame, length: int = 50, with_text: bool = False, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs(doc_id, text, ...) -> doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept_text if asked for).

    Texts are UTF-8 bytes, matches never cross documents, and strings are judged on the input. Null texts are empty.
    Rows with one doc_id count as copies of one document: none is smaller than the other. Characters that are cut in
    their middle are left out of kept_text only. An empty table gives no rows; extra columns are ignored.
    `length` is from 17 to 64.
    """
    if not GRAM < length <= 64:
        raise ValueError(f"length must be from {GRAM + 1} to 64")
    spark = docs.sparkSession
    n = partitions(spark)
    made = written(blocks(docs, block_bytes), "blocks")
    parts = 2 * n
    records = made.mapInArrow(run_records(length, parts), "part int, block long, blob binary")
    verdicts = "block long, kind int, blob binary"
    first = written(records.groupBy("part").applyInArrow(compare_runs(length), verdicts), "verdicts")
    asked = first.filter("kind = 1")
    runs = made.groupBy("block").cogroup(asked.groupBy("block")).applyInArrow(sort_block(length), "block long, blob binary")
    runs = written(runs, "runs")

    def looked_at(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, blob in _rows(b):
                prefix, sizes, rest, *_ = expand(blob, *RUN)
                s = front_decode(prefix, sizes, rest)
                yield pa.RecordBatch.from_pydict({"s": [x[:GRAM] for x in s[:: max(1, len(s) // 100)]]})

    # A row of runs is a block, of which a hundred strings or so are looked at.
    seen = drawn(runs.mapInArrow(looked_at, "s binary"), BORDER_SAMPLE, 100 * runs.count()).limit(4 * BORDER_SAMPLE).collect()
    seen = sorted(bytes(r[0]) for r in seen)
    borders = sorted({seen[i * len(seen) // n] for i in range(1, n)}) if seen else []
    merged = runs.mapInArrow(split_runs(borders), "part int, block long, blob binary").groupBy("part").applyInArrow(merge_part(length), verdicts)
    second = written(merged, "verdicts")
    discard(runs)
    told = first.filter("kind = 0").unionByName(second)
    out = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept_text string" * with_text
    return made.groupBy("block").cogroup(told.groupBy("block")).applyInArrow(cut_block(length, with_text), out)

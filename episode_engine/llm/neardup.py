"""Near-duplicate documents by HyperMinHash, banding, corrected estimates and exact verification.

A document's set of word shingles gets `bands * rows` buckets with a permutation each. A bucket stores the
leading zeros of its smallest value and ten bits after the first one, 16 bits in all; bands of these compressed
registers select candidates, a collision-corrected Jaccard estimate drops the hopeless ones, and the rest is
verified on the full sets. Equal sets meet once, as one class.

At the threshold 0.8 a band of 6 agrees with probability 0.26, so 50 bands miss a link with probability 3e-7.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, let_go, partitions, written

ROWS, BANDS = 6, 50
MANTISSA = 10
#: A pair is dropped without verification if its estimate lies this far under the threshold: near five standard errors at 300 registers.
MARGIN = 0.11
#: Ids up to which the candidates' list (8 bytes each) is broadcast to pick their texts; beyond, the join is shuffled.
BROADCAST_IDS = 1_000_000
WORD_CACHE = 400_000
#: Members of a block, of which two meet in a task, and elements of their sets.
CHUNK, ITEMS = 2048, 1_000_000
_U = np.uint64


class WordHashes(dict):
    """64-bit hashes of words; emptied when full."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORD_CACHE:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(31))) * _U(0x9E3779B97F4A7C15)
    x = (x ^ (x >> _U(29))) * _U(0xBF58476D1CE4E5B9)
    return x ^ (x >> _U(32))


def shingle_set(text: str | None, width: int, hashes: WordHashes) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct shingles: of `width` words, or of all words where there are fewer."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()  # on bytes, both know ASCII only
    if not found:
        return np.zeros(0, dtype=np.uint64)
    h = np.fromiter(map(hashes.__getitem__, found), np.uint64, len(found))
    n = min(width, len(h))
    out = np.full(len(h) - n + 1, n, dtype=np.uint64)
    for k in range(n):
        out = _mix(out + h[k : len(h) - n + 1 + k])
    return np.unique(out)


def _permutations(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(0, 2**63, count, dtype=np.uint64) * _U(2) + _U(1), rng.integers(0, 2**63, count, dtype=np.uint64)


def registers(s: np.ndarray, a: np.ndarray, c: np.ndarray) -> np.ndarray:
    """HyperMinHash registers of a non-empty set: leading zeros in the high bits, MANTISSA bits below."""
    least = np.full(len(a), 2**64 - 1, dtype=np.uint64)
    for at in range(0, len(s), 256):
        v = s[at : at + 256, None] * a[None, :]
        v += c[None, :]
        np.minimum(least, v.min(axis=0), out=least)
    bits = (least | _U(1)).astype(np.float64).view(np.uint64)
    zeros = _U(1087) - (bits >> _U(52))
    return ((zeros << _U(MANTISSA)) | ((bits >> _U(52 - MANTISSA)) & _U(2**MANTISSA - 1))).astype(np.uint16)


def band_keys(regs: np.ndarray, rows: int, bands: int) -> np.ndarray:
    r = regs.reshape(bands, rows).astype(np.uint64)
    key = np.arange(1, bands + 1, dtype=np.uint64) * _U(0xD6E8FEB86659FD93)
    for k in range(rows):
        key = _mix(key + r[:, k])
    return key.view(np.int64)


def collision_rate(na: np.ndarray, nb: np.ndarray) -> np.ndarray:
    """The chance that registers of different minima agree: summed over the cells of each octave of the hash range."""
    na, nb = na.astype(np.float64), nb.astype(np.float64)
    s, total = na + nb, np.zeros(len(na))
    for k in range(64):
        hi = 2.0**-k
        total += na * nb / s * (hi / 2 / 2**MANTISSA) * (np.exp(-s * hi / 2) - np.exp(-s * hi))
    return np.clip(total, 0, 0.5)


def estimate(same: np.ndarray, na: np.ndarray, nb: np.ndarray) -> np.ndarray:
    e = collision_rate(na, nb)
    return (same - e) / (1 - e)


def signatures(docs: DataFrame, width: int, rows: int, bands: int) -> DataFrame:
    """doc_id, n (set size), f1, f2 (a 128-bit fingerprint of the set), keys (bands), regs."""
    names = ["doc_id", "n", "f1", "f2", "keys", "regs"]

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        hashes, (a, c) = WordHashes(), _permutations(rows * bands)
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part, out = b.slice(at, 500), []
                for doc, text in zip(part.column(0).to_pylist(), part.column(1), strict=True):
                    s = shingle_set(text.as_py(), width, hashes)
                    if len(s):
                        f = np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), dtype=np.int64)
                        r = registers(s, a, c)
                        out.append((doc, len(s), int(f[0]), int(f[1]), band_keys(r, rows, bands), r.tobytes()))
                    else:
                        out.append((doc, 0, 0, 0, np.zeros(0, np.int64), b""))
                types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(zip(*out, strict=True), types, strict=True)], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(made, "doc_id long, n long, f1 long, f2 long, keys array<long>, regs binary")


def estimated(pairs: DataFrame, sigs: DataFrame, least: float) -> DataFrame:
    """pairs(a, b) whose corrected estimate reaches `least`, with the estimate as `j`."""
    side = lambda x: sigs.select(F.col("doc_id").alias(x), F.col("n").alias(f"n{x}"), F.col("regs").alias(f"r{x}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "ra", "rb")

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            for at in range(0, t.num_rows, 2000):
                p = t.slice(at, 2000)
                ra, rb = (np.frombuffer(b"".join(p.column(c).to_pylist()), np.uint16).reshape(p.num_rows, -1) for c in ("ra", "rb"))
                na, nb = p.column("na").to_numpy(), p.column("nb").to_numpy()
                j = estimate((ra == rb).mean(axis=1), na, nb)
                ok = np.flatnonzero(j >= least)
                yield pa.RecordBatch.from_arrays([p.column("a").take(pa.array(ok)), p.column("b").take(pa.array(ok)), pa.array(j[ok])], ["a", "b", "j"])

    return both.mapInArrow(judged, "a long, b long, j double")


def full_sets(docs: DataFrame, ids: DataFrame, most: int, width: int) -> DataFrame:
    """doc_id, s (the sorted shingle hashes as bytes) of the documents in ids(doc_id), of which there are `most` at most."""
    wanted = F.broadcast(ids) if most <= BROADCAST_IDS else ids
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(wanted, "doc_id", "left_semi")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        hashes = WordHashes()
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([shingle_set(t.as_py(), width, hashes).tobytes() for t in part.column(1)], pa.binary())], ["doc_id", "s"])

    return written(texts.mapInArrow(sets, "doc_id long, s binary").dropDuplicates(["doc_id"]), "sets")


def verified(pairs: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """pairs(a, b), distinct and with one a for each b, that hold 100 * intersection >= percent * union on their full sets.

    Each b's set travels to its a; a sorted partition holds one a's set at a time. An a of more than CHUNK partners is
    dealt to several tasks.
    """
    hot = pairs.groupBy("a").agg(F.count("*").alias("_n")).filter(F.col("_n") > CHUNK)  # fewer rows than pairs / CHUNK
    salt = F.when(F.col("_n").isNull(), F.lit(0).cast("long")).otherwise(F.pmod(F.xxhash64("b"), F.ceil(F.col("_n") / CHUNK)))
    ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b"))).distinct()
    made = full_sets(docs, ids, pairs.count() * 2, width)
    salted = pairs.select("a", "b").join(hot, "a", "left").select("a", salt.alias("salt"), "b")
    wanted = salted.union(salted.select("a", "salt", F.col("a").alias("b")).distinct())
    rows = wanted.join(made.withColumnRenamed("doc_id", "b"), "b").select("a", "salt", (F.col("a") != F.col("b")).alias("other"), "b", "s")

    def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = np.zeros(0, np.uint64)
        for t in batches:
            keep = []
            for a, other, b, s in zip(*[t.column(c) for c in ("a", "other", "b", "s")], strict=True):
                s = np.frombuffer(s.as_py(), np.uint64)
                if not other.as_py():
                    own = s
                    continue
                both = int((own[np.minimum(np.searchsorted(own, s), len(own) - 1)] == s).sum()) if len(own) else 0
                if 100 * both >= percent * (len(own) + len(s) - both):
                    keep.append((a.as_py(), b.as_py()))
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in keep], pa.int64()) for i in (0, 1)], ["a", "b"])

    dealt = rows.repartition(partitions(pairs.sparkSession), "a", "salt").sortWithinPartitions("a", "salt", "other", "b")
    return dealt.mapInArrow(compared, "a long, b long")


GRID = ["key", "lo", "hi", "own", "inner"]


def grid(members: DataFrame, chunk: int, items: int) -> DataFrame:
    """members(key, doc_id, c, n): the blocks (key, lo, hi) in which members of one key and different c meet, each pair once.

    The largest c of a key is its major side, all else the minor one. Either is dealt by a hash of the id into blocks of
    about `chunk` members and `items` set elements. A minor block meets every block and a major one only minor ones, so
    that a huge class beside a few others is copied once. Pairs inside a minor block are looked at where it meets the last block
    (`inner`). No window and no task holds all of a key.
    """
    per = members.groupBy("key", "c").agg(F.count("*").alias("cnt"), F.sum("n").alias("w"))
    shape = per.groupBy("key").agg(F.max(F.struct("cnt", "w", "c")).alias("top"), F.sum("cnt").alias("cnt"), F.sum("w").alias("w"), F.count("*").alias("kinds")).filter("kinds > 1")
    blocks = lambda cnt, w: F.greatest(F.ceil(cnt / F.lit(chunk)), F.ceil(w / F.lit(items)))
    shape = shape.select("key", F.col("top.c").alias("major"), blocks(F.col("top.cnt"), F.col("top.w")).alias("nb"), blocks(F.col("cnt") - F.col("top.cnt"), F.col("w") - F.col("top.w")).alias("na"))
    rows = members.join(shape, "key")
    h, major = F.xxhash64("doc_id"), F.col("c") == F.col("major")
    rows = rows.withColumn("own", F.when(major, F.col("na") + F.pmod(h, "nb")).otherwise(F.pmod(h, "na")))
    rows = rows.withColumn("d", F.explode(F.sequence(F.lit(0).cast("long"), F.when(major, F.col("na")).otherwise(F.col("na") + F.col("nb")) - 1))).filter("d != own")
    rows = rows.withColumn("lo", F.least("own", "d")).withColumn("hi", F.greatest("own", "d"))
    return rows.withColumn("inner", F.col("hi") == F.col("na") + F.col("nb") - 1).select(*GRID, "doc_id", "c", "n")


def in_blocks(rows: DataFrame, judge, schema: str) -> DataFrame:
    """judge(table) over the rows of whole blocks (key, lo, hi), in order of (key, lo, hi, own, doc_id); several small blocks come at once.

    judge returns arrays (a, b). A block is never split: the rows of a batch's last block wait for the next batch.
    """
    dealt = rows.repartition(partitions(rows.sparkSession), "key", "lo", "hi").sortWithinPartitions("key", "lo", "hi", "own", "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        wait: list[pa.RecordBatch] = []
        last = None

        def out(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.asarray(z, dtype=np.int64)) for z in judge(pa.Table.from_batches(parts))], ["a", "b"])

        for t in batches:
            for at in range(0, t.num_rows, 2 * CHUNK):
                part = t.slice(at, 2 * CHUNK)
                names = [part.column(k).to_numpy() for k in range(3)]
                final = tuple(z[-1] for z in names)
                same = np.flatnonzero((names[0] == final[0]) & (names[1] == final[1]) & (names[2] == final[2]))[0]
                if last is not None and (same > 0 or final != last):
                    yield out([*wait, part.slice(0, same)])
                    wait = []
                elif same > 0:
                    yield out([part.slice(0, same)])
                wait.append(part.slice(same))
                last = final
        if wait:
            yield out(wait)

    return dealt.mapInArrow(run, schema)


def _runs(t: pa.Table) -> np.ndarray:
    """Where the blocks of a table begin, and its length at the end."""
    key, lo, hi = (t.column(x).to_numpy() for x in GRID[:3])
    new = np.flatnonzero((key[1:] != key[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])) + 1
    return np.concatenate([[0], new, [len(key)]])


def candidate_forest(blocks: DataFrame, sigs: DataFrame, least: float, percent: int) -> DataFrame:
    """(a, b) that join, in each block, all members which a chain of pairs with estimates of `least` or more joins.

    Only pairs of different c and of fitting sizes count. A pair whose ends are joined already is not looked at: there are
    fewer rows than members, however many pairs agree.
    """

    def judge(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        own, inner, ids, n, c = (t.column(x).to_numpy() for x in ("own", "inner", "doc_id", "n", "c"))
        regs = np.frombuffer(b"".join(t.column("regs").to_pylist()), np.uint16).reshape(len(ids), -1)
        edge = _runs(t)
        end = np.repeat(edge[1:], np.diff(edge))
        label, at, found = np.arange(len(ids)), np.arange(len(ids)), []
        for d in range(1, int(np.diff(edge).max()) if len(ids) else 0):
            at = at[at + d < end[at]]
            x, y = at, at + d
            ok = (c[x] != c[y]) & (inner[x] | (own[x] != own[y])) & (100 * np.minimum(n[x], n[y]) >= percent * np.maximum(n[x], n[y]))
            x, y = x[ok], y[ok]
            for k in range(0, len(x), 4096):
                p, q = x[k : k + 4096], y[k : k + 4096]
                ok = label[p] != label[q]
                p, q = p[ok], q[ok]
                share = (regs[p] == regs[q]).mean(axis=1)
                ok = np.flatnonzero(share >= least)  # an estimate is never above the share
                p, q = p[ok], q[ok]
                ok = estimate(share[ok], n[p], n[q]) >= least
                for i, j in zip(p[ok].tolist(), q[ok].tolist(), strict=True):
                    if label[i] != label[j]:
                        label[label == label[j]] = label[i]
                        found.append((i, j))
        x, y = (np.asarray([f[k] for f in found], dtype=np.int64) for k in (0, 1))
        return ids[x], ids[y]

    rows = blocks.join(sigs.select("doc_id", "regs"), "doc_id").select(*GRID, "doc_id", "c", "n", "regs")
    return in_blocks(rows, judge, "a long, b long")


def spanning_links(blocks: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Verified links (a, b) that join the classes c of each block as all of its links would: fewer rows than classes.

    Sets of different classes are intersected in full, unless links found before have joined the two.
    """

    def of_block(ids, c, own, inner, raw) -> list[tuple[int, int]]:
        n = np.asarray([len(r) // 8 for r in raw])
        start = np.concatenate([[0], np.cumsum(n)])
        codes = np.unique(np.frombuffer(b"".join(raw), np.uint64), return_inverse=True)[1]
        here, label, out = np.zeros(int(codes.max()) + 1, dtype=np.uint8), np.unique(c, return_inverse=True)[1], []
        for x in range(len(ids) - 1):
            rest = slice(x + 1, len(ids))
            ok = (label[rest] != label[x]) & (100 * np.minimum(n[rest], n[x]) >= percent * np.maximum(n[rest], n[x]))
            ys = np.flatnonzero(ok if inner else ok & (own[rest] != own[x])) + x + 1
            if not len(ys):
                continue
            here[codes[start[x] : start[x + 1]]] = 1
            if 2 * len(ys) > len(ids) - x:
                both = np.add.reduceat(here[codes[start[x + 1] :]], start[x + 1 : -1] - start[x + 1], dtype=np.int64)[ys - x - 1]
            else:
                both = np.asarray([int(here[codes[start[y] : start[y + 1]]].sum(dtype=np.int64)) for y in ys.tolist()])
            here[codes[start[x] : start[x + 1]]] = 0
            for y in ys[100 * both >= percent * (n[x] + n[ys] - both)].tolist():
                if label[y] != label[x]:
                    label[label == label[y]] = label[x]
                    out.append((ids[x], ids[y]))
        return out

    def judge(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        ids, c, own, inner = (t.column(x).to_numpy() for x in ("doc_id", "c", "own", "inner"))
        raw, edge, out = t.column("s").to_pylist(), _runs(t), []
        for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            if j - i > 1:
                out += of_block(ids[i:j], c[i:j], own[i:j], bool(inner[i]), raw[i:j])
        return tuple(np.asarray([e[k] for e in out], dtype=np.int64) for k in (0, 1))

    rows = blocks.join(sets, "doc_id").select(*GRID, "doc_id", "c", "s")
    return in_blocks(rows, judge, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """edges(a, b) -> doc_id, component: the smallest id that can be reached. Each round hooks and halves what is left."""
    edges = written(edges.select("a", "b").distinct(), "edges")
    labels = written(edges.select(F.col("a").alias("doc_id")).union(edges.select("b")).distinct().select("doc_id", F.col("doc_id").alias("component")), "labels")
    left = edges
    while not left.isEmpty():
        up = left.select(F.greatest("a", "b").alias("component"), F.least("a", "b").alias("to")).groupBy("component").agg(F.min("to").alias("to"))
        up = written(up, "hooks")
        # Two steps of each pointer: what a hook's end is hooked to.
        twice = up.alias("x").join(up.select(F.col("component").alias("to"), F.col("to").alias("to2")), "to", "left").select("component", F.coalesce("to2", "to").alias("to"))
        twice = written(twice, "hooks")
        new = written(labels.join(twice, "component", "left").select("doc_id", F.coalesce("to", "component").alias("component")), "labels")
        ends = left
        for x in ("a", "b"):
            ends = ends.join(twice.select(F.col("component").alias(x), F.col("to").alias(f"_{x}")), x, "left").withColumn(x, F.coalesce(f"_{x}", x)).drop(f"_{x}")
        rest = written(ends.filter("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
        discard(labels, left, up, twice)
        labels, left = new, rest
    return labels


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, rows: int = ROWS, bands: int = BANDS) -> DataFrame:
    """docs(doc_id, text, ...) -> doc_id, n_shingles, component_id (the smallest doc_id reachable), kept.

    One row for each row (ids should be unique; of rows with one id each is judged by its own set). Null texts and texts
    without words have an empty set: they are linked with nothing. Copies share a class and are never compared.
    Empty tables give empty results; extra columns are ignored.
    """
    sigs = written(signatures(docs, width, rows, bands), "sigs")
    classes = written(sigs.filter("n > 0").groupBy("f1", "f2").agg(F.min("doc_id").alias("rep")), "classes")
    reps = sigs.join(classes.select("f1", "f2", F.col("rep").alias("doc_id")), ["f1", "f2", "doc_id"], "left_semi").select("doc_id", "n", "keys", "regs").dropDuplicates(["doc_id"])
    reps = written(reps, "reps")
    keyed = reps.select("doc_id", "n", F.explode("keys").alias("key"))
    shared = keyed.groupBy("key").agg(F.min("doc_id").alias("first"), F.count("*").alias("_n")).filter("_n > 1").drop("_n")
    buckets = written(keyed.join(shared, "key"), "buckets")
    least = percent / 100 - MARGIN
    fits = F.expr(f"100 * least(n, n2) >= {percent} * greatest(n, n2)")
    # First every document meets its best estimated bucket leader only.
    size = reps.select(F.col("doc_id").alias("first"), F.col("n").alias("n2"))
    star = buckets.filter("doc_id != first").select("first", "doc_id", "n").distinct().join(size, "first").filter(fits).select(F.col("first").alias("a"), F.col("doc_id").alias("b"))
    star = written(estimated(star, reps, least).groupBy("b").agg(F.max_by("a", F.struct("j", -F.col("a"))).alias("a")).select("a", "b"), "star")
    first_edges = written(verified(star, docs, width, percent), "links")
    found = components(first_edges)
    # Then members of a bucket that are still in different components meet. Estimates join them to candidate groups, as
    # forests; inside a group all that are in different components are compared on full sets, and links come as forests too.
    named = buckets.join(found, "doc_id", "left").select("key", "doc_id", "n", F.coalesce("component", "doc_id").alias("c"))
    forest = written(candidate_forest(grid(named, CHUNK, ITEMS), reps, least, percent).distinct(), "forest")
    spent = [reps, buckets, star, first_edges, forest]
    if not forest.isEmpty():
        groups = written(components(forest), "groups")
        members = groups.join(reps.select("doc_id", "n"), "doc_id").join(found.withColumnRenamed("component", "c"), "doc_id", "left")
        members = members.select(F.col("component").alias("key"), "doc_id", F.coalesce("c", "doc_id").alias("c"), "n")
        sets = full_sets(docs, groups.select("doc_id"), groups.count(), width)
        more = written(spanning_links(grid(members, CHUNK, ITEMS), sets, percent), "links")
        found = components(first_edges.select("a", "b").union(more)) if not more.isEmpty() else found
        spent += [groups, sets, more]
    discard(*spent)  # what is left to do reads sets' fingerprints and components only
    comp = classes.join(found.withColumnRenamed("doc_id", "rep"), "rep", "left").select("f1", "f2", F.coalesce("component", "rep").alias("component"))
    out = sigs.select("doc_id", "n", "f1", "f2").join(comp, ["f1", "f2"], "left")
    component = F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), (F.col("doc_id") == component).alias("kept"))

"""Dice co-occurrence of items that share many short sessions, without a table of all pairs.

Pairs of items are many more than those that pass a cut. Items are numbered from the rarest to the commonest, and the
numbers are cut into blocks of about equal work. A session goes to each block that one of its items is in, from that
item on: the block counts what follows its own items, in slices of a bounded number of pairs, and gives only pairs that
pass. What is shuffled are sessions, never pairs. As no more sessions are shared than the rarer item has, an item
more than 2 / cut - 1 times as common cannot pass, and a block's sessions end before such items.

Items are known by their 64-bit hash. The dictionary of items that are common enough is held by the driver and each worker, 12 bytes
an item, up to MAX_ITEMS; beyond that, and if two hashes agree, all pairs are joined.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..runtime import keep

#: Items of the dictionary; items of sessions behind one block, about; pairs that a block counts at a time.
MAX_ITEMS, BLOCK_ITEMS, SLICE_PAIRS = 2_000_000, 2_000_000, 1_000_000
#: Blocks at least.
LEAST_BLOCKS = 12


def _blocks(n: np.ndarray, ratio: float, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """(first item of each block, end of what its items can be paired with); n: ascending sizes of the items.

    The work of an item is taken to be its size times that of the items behind it; this decides how even blocks are, nothing else.
    """
    end = np.searchsorted(n, n * ratio * (1 + 1e-9) + 1, side="right")
    upto = np.concatenate(([0.0], np.cumsum(n, dtype="float64")))
    work = np.cumsum(n * (upto[end] - upto[1:]))
    first = np.unique(np.searchsorted(work, work[-1] * np.arange(blocks) / blocks))
    first[0] = 0
    first = first[first < len(n)]
    last = np.concatenate((first[1:], [len(n)])) - 1
    return first, end[last]


def _dealer(known):
    """Kernel over item hashes of sessions: for each block that a batch meets, its sessions' lengths and numbers, counted from the commonest, packed."""
    import pyarrow as pa

    def packs(no, size, start, long):
        ends = np.cumsum(long)
        take = np.repeat(start - ends + long, long) + np.arange(ends[-1])
        cells = np.concatenate((long, size - 1 - no[take])).astype("<u4").view(np.uint8).reshape(-1, 4)
        # bytes of one place together: most are small
        return len(long), len(take), pa.compress(cells.T.tobytes(), codec="zstd", asbytes=True)

    def run(batches):
        hashes, number, first, stop = known.value[:4]
        size = len(hashes)
        for batch in batches:
            lists = batch.column(0)
            values = lists.flatten().to_numpy(zero_copy_only=False)
            row = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
            at = np.minimum(np.searchsorted(hashes, values), size - 1)
            hit = hashes[at] == values
            key = np.sort(row[hit] * size + number[at[hit]])
            if not len(key):
                continue
            row, no = np.divmod(key, size)
            block = np.searchsorted(first, no, side="right") - 1
            new = np.concatenate(([True], (row[1:] != row[:-1]) | (block[1:] != block[:-1])))
            start = np.flatnonzero(new)
            long = np.searchsorted(key, row[start] * size + stop[block[start]]) - start
            order = np.argsort(block[start], kind="stable")
            start, long = start[order][long[order] > 1], long[order][long[order] > 1]
            blocks, at = np.unique(block[start], return_index=True)
            packed = [packs(no, size, start[x:y], long[x:y]) for x, y in zip(at, [*at[1:], len(start)])]
            columns = [pa.array(blocks, pa.int32()), *[pa.array([p[i] for p in packed], t) for i, t in enumerate((pa.int32(), pa.int32(), pa.binary()))]]
            yield pa.RecordBatch.from_arrays(columns, names=["block", "rows", "numbers", "packed"])

    return run


def _counter(known, cut: float, min_support: int, slice_pairs: int):
    """Kernel over the sessions of blocks: pairs that pass, by hash, with their counts."""
    import pyarrow as pa

    def passed(a, b, both, hash_of, n):
        na, nb = n[a], n[b]
        ok = (both >= min_support) & (2.0 * both / (na + nb) >= cut)
        a, b = a[ok], b[ok]
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (hash_of[a], hash_of[b], both[ok], na[ok], nb[ok])], names=["ha", "hb", "both", "na", "nb"])

    def counted(flat, ends, lo, hi, hash_of, n):
        size = len(n)
        own = np.flatnonzero((flat >= lo) & (flat < hi)).astype(np.int32)
        rest = (np.repeat(ends, np.diff(np.concatenate(([0], ends))))[own] - own - 1).astype(np.int32)
        order = np.argsort(flat[own], kind="stable")
        own, rest = own[order], rest[order]
        a = flat[own]
        begins = np.flatnonzero(np.concatenate(([True], a[1:] != a[:-1])))
        upto = np.concatenate(([0], np.cumsum(rest, dtype=np.int64)))
        begins = np.append(begins, len(a))
        pairs, i = upto[begins], 0

        def behind(x, y):
            k = rest[x:y]
            return flat[np.repeat(own[x:y] + 1 - (upto[x:y] - upto[x]), k) + np.arange(upto[y] - upto[x])]

        while i < len(begins) - 1:
            j = max(i + 1, int(np.searchsorted(pairs, pairs[i] + slice_pairs, side="right")) - 1)
            x, y = int(begins[i]), int(begins[j])
            if pairs[j] - pairs[i] > slice_pairs:  # one item with very many sessions
                total = np.zeros(size, np.int64)
                while x < y:
                    z = min(y, max(x + 1, int(np.searchsorted(upto, upto[x] + slice_pairs, side="right")) - 1))
                    total += np.bincount(behind(x, z), minlength=size)
                    x = z
                b = np.flatnonzero(total)
                yield passed(np.full(len(b), a[begins[i]]), b, total[b], hash_of, n)
            elif pairs[j] > pairs[i]:
                key = np.sort(np.repeat(a[x:y].astype(np.int64) * size, rest[x:y]) + behind(x, y))
                new = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
                both = np.diff(np.append(new, len(key)))
                new, both = new[both >= min_support], both[both >= min_support]
                yield passed(*np.divmod(key[new], size), both, hash_of, n)
            i = j

    def run(batches):
        first, _, hash_of, n = known.value[2:]
        parts: dict = {}
        for batch in batches:
            for block, rows, numbers, packed in zip(*(batch.column(c).to_pylist() for c in ("block", "rows", "numbers", "packed"))):
                raw = np.frombuffer(pa.decompress(packed, 4 * (rows + numbers), codec="zstd"), np.uint8)
                cells = raw.reshape(4, -1).T.copy().view("<i4").ravel()
                got = parts.setdefault(block, ([], []))
                got[0].append(len(n) - 1 - cells[rows:])
                got[1].append(cells[:rows])
        for block in sorted(parts):
            flats, longs = parts.pop(block)
            flat, ends = np.concatenate(flats), np.cumsum(np.concatenate(longs)).astype(np.int32)
            del flats, longs
            yield from counted(flat, ends, first[block], first[block + 1] if block + 1 < len(first) else len(n), hash_of, n)

    return run


def dice_pairs(sessions: DataFrame, cut: float, min_item: int = 1, min_support: int = 1, max_items: int | None = None, slice_pairs: int | None = None) -> DataFrame | None:
    """(a, b, both, na, nb) of items a < b whose Dice weight reaches the cut, which is above 0; sessions: (items), arrays of different texts.

    None if the dictionary is beyond its bound or two of its hashes agree: then the caller joins all pairs.
    """
    spark = sessions.sparkSession
    words = keep(sessions.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("n")).where(F.col("n") >= min_item), "items")
    if words.count() > (MAX_ITEMS if max_items is None else max_items):
        return None
    rows = words.select(F.xxhash64("item").alias("h"), "n").toArrow()  # at most MAX_ITEMS rows
    hashes, n = rows.column("h").to_numpy(), rows.column("n").to_numpy()
    if len(np.unique(hashes)) < len(hashes):
        return None
    order = np.lexsort((hashes, n))
    hash_of, n = hashes[order], n[order]
    by_hash = np.argsort(hash_of)
    if not len(n):
        return words.limit(0).selectExpr("item as a", "item as b", "n as both", "n as na", "n as nb")
    first, stop = _blocks(n, 2 / cut - 1, max(LEAST_BLOCKS, -(-int(n.sum()) // BLOCK_ITEMS)))
    known = spark.sparkContext.broadcast((hash_of[by_hash], by_hash.astype(np.int32), first, stop, hash_of, n))
    dealt = sessions.select(F.transform("items", lambda x: F.xxhash64(x)).alias("items")).mapInArrow(_dealer(known), "block int, rows int, numbers int, packed binary")
    dealt = dealt.repartitionById(len(first), F.col("block"))
    found = keep(dealt.mapInArrow(_counter(known, cut, min_support, slice_pairs or SLICE_PAIRS), "ha long, hb long, both long, na long, nb long"), "item-pairs")
    named = words.select(F.xxhash64("item").alias("h"), "item")
    x, y = named.toDF("ha", "x"), named.toDF("hb", "y")
    pairs = found.join(x, "ha").join(y, "hb")
    turn = F.col("x") < F.col("y")
    return pairs.select(
        F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "both", F.when(turn, F.col("na")).otherwise(F.col("nb")).alias("na"), F.when(turn, F.col("nb")).otherwise(F.col("na")).alias("nb"))

"""Substring dedup by relative Lempel-Ziv parsing: every document is factored greedily against a reference in blocks.

The reference is what the corpus says for the first time: each window of W words at its first place (by row key, then
position). A greedy factor starts at the first word whose window the reference holds elsewhere or first, and runs on
as long as the reference text runs on with the document; the next factor starts behind its last word. A window stands in the
reference once, so the longest match is unique. Factors are at least W words long and all of them are duplicate spans. The windows that
straddle the end of a factor belong to no factor; they are checked one by one, and those that occur elsewhere are spans too.

The index of the reference lies in blocks by anchor: the anchor of a window is its smallest hashed K-gram, and a phrase
is a maximal run of windows with one anchor, so equal text is cut alike wherever it stands. A phrase meets every place
in the only block that can hold it. A phrase that occurs elsewhere as a whole refers to its first place; the windows of a phrase that
differs (as at the ends of a passage) are looked up one by one, and so are those of the first place of a phrase
whose anchor has other phrases, as a window in it may have come earlier. Each window has one anchor, so every window is
decided, by 128 bits of hashes.

Hot passages: counts are aggregated before shuffles, and joins back to occurrences are equi-joins that Spark can split.
Texts are shuffled once, by document; both later readings share that exchange.

Edge cases: null texts have no words; texts under W words keep all; rows that repeat (equal or not, with equal ids) count
as places of their own; ids of any type and null ids are kept (a row's key is its id, or a hash of it, and a hash of its text); an empty
table gives no rows; extra columns are ignored; a very long text is one slice of its own and only adds phrases.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .kernels import OTHER_BASE, WORD_BASE, PowerTable, Prefix, Words, gram_hashes, signed, slices, sliding_min, string_views

common.by_value(__name__)

WINDOW, GRAM = 35, 8
#: Low bits that hold a place in a slice while minima are taken; more in slices of more words.
_PLACE_BITS = 24


def phrases_of(words: Words, tables: dict, window: int = WINDOW, gram: int = GRAM):
    """(first window, windows, anchor, phrase) of each phrase of a slice; word numbers within the slice."""
    grams = gram_hashes(words.hash, gram)
    empty = np.zeros(0, np.int64)
    if len(words) < window:
        return empty, empty, empty.view(np.uint64), empty.view(np.uint64)
    low = np.uint64((1 << max(_PLACE_BITS, len(grams).bit_length())) - 1)
    place = (grams & ~low) | np.arange(len(grams), dtype=np.uint64)
    least = sliding_min(place, window - gram + 1)
    first, last = words.first[:-1], words.first[1:] - window  # windows of a document start in [first, last]
    mark = np.zeros(len(least) + 1, np.int64)
    has = last >= first
    np.add.at(mark, first[has], 1)
    np.add.at(mark, last[has] + 1, -1)
    valid = np.cumsum(mark)[:-1] > 0
    at = np.flatnonzero(valid)
    if not len(at):
        return empty, empty, empty.view(np.uint64), empty.view(np.uint64)
    new = np.concatenate(([True], least[at[1:]] != least[at[:-1]]))
    start = at[new]
    n = np.diff(np.concatenate((np.flatnonzero(new), [len(at)])))
    anchor = grams[(least[start] & low).astype(np.int64)]
    text = Prefix(words.hash, tables.setdefault("other", PowerTable(OTHER_BASE)))
    return start, n, anchor, text.of(start, start + n + window - 1)


def phrase_rows(batches):
    tables: dict = {}
    for batch in batches:
        data, offs = string_views(batch.column("text"))
        for lo, hi in slices(offs):
            w = Words(data, offs[lo : hi + 1], tables)
            start, n, anchor, phrase = phrases_of(w, tables)
            doc = np.searchsorted(w.first, start, side="right") - 1
            row = pa.array(doc + lo)
            yield pa.RecordBatch.from_arrays(
                [pa.array(signed(anchor)), pa.array(signed(phrase)), batch.column("kid").take(row), batch.column("th").take(row), pa.array((start - w.first[doc]).astype(np.int32)), pa.array(n.astype(np.int32))],
                names=["anchor", "phrase", "kid", "th", "pos", "n"],
            )


def _lists(column: pa.Array) -> tuple[np.ndarray, list[np.ndarray]]:
    """Row of each entry and the fields of a list-of-struct column; null lists are empty."""
    lengths = np.array(column.value_lengths().fill_null(0), np.int64)
    flat = column.flatten()
    return np.repeat(np.arange(len(column)), lengths), [np.asarray(flat.field(i), np.int64) for i in range(flat.type.num_fields)]


def counted(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """first, first + 1, .. (n of them) for each entry."""
    return np.repeat(first - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)


def window_rows(batches):
    """The windows of phrases to check: two hashes each."""
    tables: dict = {}
    for batch in batches:
        data, offs = string_views(batch.column("text"))
        row, (pos, n, known) = _lists(batch.column("todo"))
        for lo, hi in slices(offs):
            w = Words(data, offs[lo : hi + 1], tables)
            mine = (row >= lo) & (row < hi)
            r, p, m, k = row[mine], pos[mine], n[mine], known[mine]
            doc = np.repeat(r, m)
            at = counted(p, m)
            start = at + w.first[doc - lo]
            one = Prefix(w.hash, tables.setdefault("word", PowerTable(WORD_BASE))).of(start, start + WINDOW)
            two = Prefix(w.hash, tables.setdefault("other", PowerTable(OTHER_BASE))).of(start, start + WINDOW)
            take = pa.array(doc)
            yield pa.RecordBatch.from_arrays(
                [pa.array(signed(one)), pa.array(signed(two)), batch.column("kid").take(take), batch.column("th").take(take), pa.array(at.astype(np.int32)), pa.array(np.repeat(k, m).astype(bool)), pa.array(np.repeat(p, m).astype(np.int32))],
                names=["w1", "w2", "kid", "th", "pos", "known", "phrase_pos"],
            )


class Parse:
    """The greedy parse of the documents of one slice."""

    def __init__(self, w: Words, row: np.ndarray, found: list[np.ndarray]):
        """row: document within the slice of each run of windows; found: pos, n, key and text hash and position of the reference, rank."""
        pos, n, rk, rt, rp, rank = found
        size = len(w)
        has = np.zeros(size + 1, bool)
        ref = [np.zeros(size + 1, np.int64) for _ in range(3)]
        order = np.argsort(rank, kind="stable")  # a window looked up by itself knows better than its phrase
        start, m = (pos + w.first[row])[order], n[order]
        at = counted(start, m)
        has[at] = True
        for out, x in zip(ref, (rk, rt, rp)):
            out[at] = np.repeat(x[order], m)
        ref[2][at] += at - np.repeat(start, m)
        runs_on = has[1:] & has[:-1] & (ref[0][1:] == ref[0][:-1]) & (ref[1][1:] == ref[1][:-1]) & (ref[2][1:] == ref[2][:-1] + 1)
        head = has & ~np.concatenate(([False], runs_on))
        self.first = np.flatnonzero(head)
        inner = np.flatnonzero(has)
        self.length = np.diff(np.append(np.searchsorted(inner, self.first), len(inner)))
        self.doc = np.searchsorted(w.first, self.first, side="right") - 1
        self.ref = [x[self.first] for x in ref]
        self._factor()

    def _factor(self) -> None:
        """Walks each document's chains of windows: a chain gives a factor from the first word behind the factor before on."""
        starts, sizes, chains, checks = [], [], [], []  # checks: (first window, windows) that straddle a factor's end
        doc, end = -1, 0
        for k, (d, s, m) in enumerate(zip(self.doc.tolist(), self.first.tolist(), self.length.tolist())):
            if d != doc:
                doc, end = d, 0
            skipped = min(m, max(0, end - s))
            if skipped:
                checks.append((s, skipped))
            if skipped < m:
                starts.append(s + skipped)
                sizes.append(m - skipped + WINDOW - 1)
                chains.append(k)
                end = starts[-1] + sizes[-1]
        self.start, self.size, self.chain = (np.array(x, np.int64) for x in (starts, sizes, chains))
        self.checks = np.array(checks, np.int64).reshape(-1, 2)

    def covered(self, size: int) -> np.ndarray:
        """Which words the factors and the windows at their boundaries cover."""
        cover = np.zeros(size + 1, np.int64)
        np.add.at(cover, self.start, 1)
        np.add.at(cover, self.start + self.size, -1)
        np.add.at(cover, self.checks[:, 0], 1)
        np.add.at(cover, self.checks.sum(1) + WINDOW - 1, -1)
        return np.cumsum(cover)[:-1] > 0


def parses(batches):
    """(batch, first row, row behind the last, words, parse) of each slice."""
    tables: dict = {}
    for batch in batches:
        data, offs = string_views(batch.column("text"))
        row, found = _lists(batch.column("runs"))
        for lo, hi in slices(offs):
            w = Words(data, offs[lo : hi + 1], tables)
            mine = (row >= lo) & (row < hi)
            yield batch, lo, hi, w, Parse(w, row[mine] - lo, [x[mine] for x in found])


def stripped(with_text: bool):
    def run(batches):
        for batch, lo, hi, w, parse in parses(batches):
            kept = ~parse.covered(len(w))
            before = np.concatenate(([0], np.cumsum(kept)))
            ws, size = w.start[kept], (w.end - w.start)[kept] + 1
            out = np.full(int(size.sum()), 32, np.uint8)
            ends = np.concatenate(([0], np.cumsum(size)))
            index = np.arange(len(out)) + np.repeat(ws - ends[:-1], size)
            inner = np.ones(len(out), bool)
            inner[ends[1:] - 1] = False
            out[inner] = w.data[index[inner]]
            raw = memoryview(out)
            words, left = np.diff(w.first), np.diff(before[w.first])
            edge = ends[before[w.first]]
            texts = [bytes(raw[a : b - 1]) if b > a else b"" for a, b in zip(edge[:-1], edge[1:])]
            cols = [batch.column("doc_id").slice(lo, hi - lo), pa.array(words.astype(np.int64)), pa.array((words - left).astype(np.int64)), pa.array([hashlib.sha256(t).hexdigest() for t in texts], pa.string())]
            if with_text:
                cols.append(pa.array([t.decode("utf-8", "replace") for t in texts], pa.string()))
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_words", "n_removed", "kept_sha256", *["kept_text"] * with_text])

    return run


def factor_rows(batches):
    """The factors of the parse, one row each."""
    for batch, lo, _, w, parse in parses(batches):
        doc, shift = parse.doc[parse.chain], parse.start - parse.first[parse.chain]
        row = pa.array(doc + lo)
        ref = [x[parse.chain] for x in parse.ref]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id").take(row), batch.column("kid").take(row), pa.array(parse.start - w.first[doc]), pa.array(parse.size), pa.array(ref[0]), pa.array(ref[2] + shift)],
            names=["doc_id", "row_key", "start", "n_words", "ref_key", "ref_start"],
        )


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and a key of the row that is never null: kid (the id as a number, or a hash) and th (of the text)."""
    text = F.coalesce("text", F.lit(""))
    return docs.select("doc_id", text.alias("text"), F.coalesce(common.number_of_id(docs), F.xxhash64(text)).alias("kid"), F.xxhash64(text).alias("th"))


def lookups(rows: DataFrame) -> DataFrame:
    """Every phrase whose anchor is known elsewhere: kid, th, pos, n, ref (its first place), copy (it occurs elsewhere), others (phrases of its anchor)."""
    found = rows.select("kid", "th", "text").mapInArrow(phrase_rows, "anchor bigint, phrase bigint, kid bigint, th bigint, pos int, n int")
    # written apart: then both sides of each join are plain exchanges, whose hot keys Spark splits
    live = common.spill(found.groupBy("anchor").count().where("count > 1").select("anchor"), "rlz-live")
    known = common.spill(found.join(live, "anchor", "left_semi"), "rlz-known")
    first = known.groupBy("anchor", "phrase").agg(F.count("*").alias("copies"), F.min(F.struct("kid", "th", "pos")).alias("ref"))
    first = common.spill(first, "rlz-first")
    blocks = common.spill(first.groupBy("anchor").agg(F.count("*").alias("others")), "rlz-blocks")
    index = common.spill(first.join(blocks, "anchor"), "rlz-index")
    out = known.join(index, ["anchor", "phrase"]).select("kid", "th", "pos", "n", (F.col("copies") > 1).alias("copy"), "others", "ref")
    out = common.spill(out, "rlz-lookups")
    common.release(live, known, first, blocks, index)
    return out


def runs_of(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """(kid, th, runs: list of windows that occur elsewhere, with their place in the reference); rows: keyed, partitioned by key."""
    phrases = lookups(keyed(docs))
    own = F.struct("kid", "th", "pos")
    check = (~F.col("copy")) | ((F.col("others") > 1) & (own == F.col("ref")))
    todo = phrases.where(check).groupBy("kid", "th").agg(F.collect_list(F.struct("pos", "n", F.col("copy").cast("int").alias("known"))).alias("todo"))
    windows = rows.join(todo, ["kid", "th"]).select("kid", "th", "text", "todo").mapInArrow(window_rows, "w1 bigint, w2 bigint, kid bigint, th bigint, pos int, known boolean, phrase_pos int")
    again = windows.groupBy("w1", "w2").agg(F.count("*").alias("places"), F.min(own).alias("ref")).where("places > 1").drop("places")
    placed = common.spill(windows.join(again, ["w1", "w2"]).select("kid", "th", "pos", "known", "phrase_pos", "ref"), "rlz-placed")
    run = lambda pos, n, ref, rank: F.struct(pos.alias("pos"), n.alias("n"), ref["kid"].alias("rk"), ref["th"].alias("rt"), ref["pos"].alias("rp"), F.lit(rank).alias("rank"))
    copied = phrases.where("copy").select("kid", "th", run(F.col("pos"), F.col("n"), F.col("ref"), 0).alias("run"))
    checked = placed.where("not known").select("kid", "th", run(F.col("pos"), F.lit(1), F.col("ref"), 1).alias("run"))
    # windows of a copied phrase that came earlier in another phrase: all its copies refer to that place
    moved = placed.where(F.col("known") & (own != F.col("ref"))).select(F.struct("kid", "th", F.col("phrase_pos").alias("pos")).alias("phrase"), (F.col("pos") - F.col("phrase_pos")).alias("shift"), F.col("ref").alias("earlier"))
    moved = common.spill(moved, "rlz-moved")
    again = phrases.where("copy and others > 1").join(moved, F.col("ref") == F.col("phrase")).select("kid", "th", run(F.col("pos") + F.col("shift"), F.lit(1), F.col("earlier"), 1).alias("run"))
    return copied.unionByName(checked).unionByName(again).groupBy("kid", "th").agg(F.collect_list("run").alias("runs"))


def parsed(docs: DataFrame, width: int | None = None) -> DataFrame:
    """doc_id, kid, text, runs of every row."""
    rows = keyed(docs).repartition(width or common.shuffle_width(docs.sparkSession), "kid", "th")
    return rows.join(runs_of(docs, rows), ["kid", "th"], "left").select("doc_id", "kid", "text", "runs")


def dedup(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256[, kept_text]) for every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return parsed(docs).mapInArrow(stripped(with_text), f"doc_id {kind}, n_words bigint, n_removed bigint, kept_sha256 string{', kept_text string' if with_text else ''}")


def factors(docs: DataFrame) -> DataFrame:
    """(doc_id, row_key, start, n_words, ref_key, ref_start): the factors of every row. A passage's first place refers to itself."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return parsed(docs).mapInArrow(factor_rows, f"doc_id {kind}, row_key bigint, start bigint, n_words bigint, ref_key bigint, ref_start bigint")


def op2_substring_rlz(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(common.table(spark, sf_dir, "documents"))


ORACLE = r"""
with d as (select row_number() over () as rn, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
p as (select rn, p, md5(array_to_string(w[p:p + 34], ' ')) as h from (select rn, w, unnest(range(1, len(w) - 33)) as p from d where len(w) >= 35)),
dup as (select rn, p from (select rn, p, count(*) over (partition by h) as c from p) where c > 1),
hit as (select distinct rn, unnest(range(p, p + 35)) as q from dup),
k as (select d.rn, list(d.word order by d.q) as kept from (select rn, unnest(w) as word, unnest(range(1, len(w) + 1)) as q from d) d anti join hit on d.rn = hit.rn and d.q = hit.q group by d.rn)
select doc_id, len(w)::bigint as n_words, (len(w) - coalesce(len(kept), 0))::bigint as n_removed, sha256(coalesce(array_to_string(kept, ' '), '')) as kept_sha256 from d left join k using (rn)
"""

"""N-gram Jaccard join: rare-first prefix filtering with length, positional and suffix filters.

A document's set holds its different word 5-grams; two documents link when 100 * shared >= 75 * united.

Order: grams stand rare-first, by counts over all documents in a table of fixed size (hashed slots; a slot shared by
several grams only blurs the order), then by hash. Two linked sets share a gram among their first n - ceil(0.75 n) + 1
grams, so only these are posted.
Equal sets are one class from the start, each task posts a class once, and only classes are compared.
Round one checks neighbours: in each posting list, in order of set size, each class with the one before it.
Round two checks the members of long lists with the list's hub, the class whose grams are the most shared; in a family of
near copies that is a text close to all others. Both rounds make a number of pairs in proportion to the lists, and a
family, however large, falls together. The last round compares what is left: classes of different components that
share a posted gram.
Filters before a pair's texts are read: sizes within 0.75; the places of the shared gram leave room for the grams needed,
a = ceil(3 (n + m) / 7); a count: a linked pair's posted prefixes share at least min(a - n + p) grams over both sides, p
grams being posted, so the two short prefixes are intersected first; and the suffix filter: pivots split both sets again and
again, and two sets share at most the sum over the last parts of the smaller part. The pivots are the quantiles of the grams' hashes,
the same for all sets, so a set is split once and not once a pair; the depth follows the set's size (some two to four
grams a part) up to MAX_DEPTH, and of two sets the finer parts are merged.
Every pair is verified once, on its texts' whole sets. Links within one component add nothing to the answer.

Hot keys: a family's postings spread over its prefix grams, frequent grams stand last and are rarely posted; class and
component joins are equi-joins over pre-aggregated sides.

Edge cases: ids may be of any type that has an order; null, empty and wordless texts have no grams and link with nothing; with one to four words the whole
sequence is the one gram; equal rows are one class; rows with a null id take part (a set that only they hold is found again
by a hash of its text), and a component of null ids alone has a null id, of which `keep_one` keeps one row; an empty table
gives no rows; extra columns are ignored (`classes`) or kept (`keep_one`); a very long text is one slice of its own.
Grams are compared by 64-bit hashes. A class is named by 64 bits; where two sets share a name, which 128 bits tell, both get the other
half's name before anything is joined.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph.components import components
from . import common
from .kernels import OTHER_BASE, WORD_BASE, PowerTable, Prefix, Words, gram_hashes, mixed, signed, slices, string_views, tidy

common.by_value(__name__)

GRAM = 5
#: Slots of the count table (2^18 32-bit sums are 1 MB for every executor), in chunks of 2^12.
SLOT_BITS, CHUNK_BITS = 18, 12
#: Most bytes of ids (as text) that are broadcast; more are joined by a shuffle.
BROADCAST_BYTES = 16_000_000
#: The suffix filter splits a set at most so many times in two; bits of a class's first name.
MAX_DEPTH, NAME_BITS = 9, 64
#: Lists of at least so many classes get rounds of checks against their hub before all that is left is compared.
HUB_LIST, HUB_ROUNDS = 12, 1
_SALT = 0x5851F42D4C957F2D


def sets_of(data: np.ndarray, offsets: np.ndarray, tables: dict) -> tuple[np.ndarray, np.ndarray]:
    """(document, gram) of the different grams of each document, sorted by both."""
    w = Words(data, offsets, tables, lower=True)
    count = np.diff(w.first)
    grams = gram_hashes(w.hash, GRAM)
    doc = np.searchsorted(w.first, np.arange(len(grams)), side="right") - 1
    inside = np.arange(len(grams)) + GRAM <= w.first[doc + 1] if len(grams) else np.zeros(0, bool)
    short = np.flatnonzero((count > 0) & (count < GRAM))
    whole = Prefix(w.hash, tables.setdefault("other", PowerTable(OTHER_BASE))).of(w.first[short], w.first[short + 1])
    doc, grams = np.concatenate((doc[inside], short)), np.concatenate((grams[inside], whole))
    order = np.lexsort((grams, doc))
    doc, grams = doc[order], grams[order]
    if not len(doc):
        return doc, grams
    new = np.concatenate(([True], (doc[1:] != doc[:-1]) | (grams[1:] != grams[:-1])))
    return doc[new], grams[new]


def signatures(doc: np.ndarray, grams: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(set size, 64-bit sum that names the set, another name from both that sum and a second one)"""
    size = np.bincount(doc, minlength=n_docs)
    sums, other = np.zeros(n_docs, np.uint64), np.zeros(n_docs, np.uint64)
    has = np.flatnonzero(size)
    if len(has):
        first = np.concatenate(([0], np.cumsum(size[has])[:-1]))
        one = np.add.reduceat(mixed(grams ^ np.uint64(_SALT)), first) + size[has].astype(np.uint64)
        two = np.add.reduceat(mixed(grams + np.uint64(_SALT)), first)
        sums[has], other[has] = mixed(one) >> np.uint64(64 - NAME_BITS), mixed(one ^ mixed(two))
    return size, sums, other


def shapes(doc: np.ndarray, grams: np.ndarray, size: np.ndarray) -> pa.ListArray:
    """How many grams of each document fall between neighbouring pivots."""
    depth = np.clip(np.frexp(size)[1] - 2, 0, MAX_DEPTH).astype(np.int64)
    parts = np.where(size > 0, np.int64(1) << depth, 0)
    ends = np.concatenate(([0], np.cumsum(parts)))
    part = ((grams >> np.uint64(1)) >> (63 - depth[doc]).astype(np.uint64)).astype(np.int64)
    counts = np.bincount(ends[doc] + part, minlength=ends[-1]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(counts))


def slot_of(grams: np.ndarray) -> np.ndarray:
    return (mixed(grams) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


def profile(batches):
    """A row a document, and at the end the task's counts by slot."""
    tables: dict = {}
    counts = np.zeros(1 << SLOT_BITS, np.int64)
    names = ["doc_id", "key", "n", "sig", "other", "shape", "chunk", "sums"]
    kind = None
    for batch in batches:
        kind = batch.column("doc_id").type
        data, offs = string_views(batch.column("text"))
        for lo, hi in slices(offs):
            doc, grams = sets_of(data, offs[lo : hi + 1], tables)
            counts += np.bincount(slot_of(grams), minlength=1 << SLOT_BITS)
            size, sig, other = signatures(doc, grams, hi - lo)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(lo, hi - lo), batch.column("key").slice(lo, hi - lo), pa.array(size.astype(np.int32)), pa.array(signed(sig)), pa.array(signed(other)), shapes(doc, grams, size), pa.nulls(hi - lo, pa.int32()), pa.nulls(hi - lo, pa.binary())], names=names)
    if kind is not None and counts.any():
        k = 1 << (SLOT_BITS - CHUNK_BITS)
        blobs = [c.tobytes() for c in counts.reshape(k, -1)]
        yield pa.RecordBatch.from_arrays([pa.nulls(k, kind), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int32()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.list_(pa.int32())), pa.array(range(k), pa.int32()), pa.array(blobs, pa.binary())], names=names)


def adder(batches):
    sums: dict[int, np.ndarray] = {}
    for batch in batches:
        for k, blob in zip(batch.column("chunk").to_pylist(), batch.column("sums").to_pylist()):
            sums[k] = sums.get(k, 0) + np.frombuffer(blob, np.int64)
    yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([s.tobytes() for s in sums.values()], pa.binary())], names=["chunk", "sums"])


def prefix_size(n):
    """n - ceil(0.75 n) + 1"""
    return n - (3 * n + 3) // 4 + 1


def poster(ranks, with_other: bool):
    """A row for each gram of the prefix of each set, each set once a task."""

    def run(batches):
        tables: dict = {}
        seen: set = set()
        rank = ranks.value
        for batch in batches:
            data, offs = string_views(batch.column("text"))
            for lo, hi in slices(offs):
                doc, grams = sets_of(data, offs[lo : hi + 1], tables)
                size, sig, other = signatures(doc, grams, hi - lo)
                names = other.tolist()
                fresh = np.zeros(hi - lo, bool)
                for i in np.flatnonzero(size).tolist():
                    if names[i] not in seen:
                        seen.add(names[i])
                        fresh[i] = True
                mine = fresh[doc]
                doc, grams = doc[mine], grams[mine]
                order = np.lexsort((rank[slot_of(grams)], doc))  # stable: ties stay in hash order
                doc, grams = doc[order], grams[order]
                first = np.searchsorted(doc, doc)
                pos = np.arange(len(doc)) - first
                posted = pos < prefix_size(size[doc])
                doc, grams, pos = doc[posted], grams[posted], pos[posted]
                cols = [pa.array(signed(grams)), pa.array(signed(sig[doc])), pa.array(size[doc].astype(np.int32)), pa.array(pos.astype(np.int32))]
                cols += [pa.array(signed(other[doc]))] * with_other
                yield pa.RecordBatch.from_arrays(cols, names=["gram", "sig", "n", "pos", *["other"] * with_other])

    return run


def verifier(batches):
    """Pairs whose whole sets reach the threshold; both texts must have the set they are named by."""
    tables: dict = {}
    for batch in batches:
        a, ao = string_views(batch.column("text_a"))
        b, bo = string_views(batch.column("text_b"))
        want_a, want_b = (np.asarray(batch.column(c)) for c in ("a", "b"))
        good = np.zeros(batch.num_rows, bool)
        both = ao + bo
        for lo, hi in slices(both):
            da, ga = sets_of(a, ao[lo : hi + 1], tables)
            db, gb = sets_of(b, bo[lo : hi + 1], tables)
            (na, *sa), (nb, *sb) = signatures(da, ga, hi - lo), signatures(db, gb, hi - lo)
            named = [np.logical_or(*(signed(x) == want[lo:hi] for x in s)) for s, want in ((sa, want_a), (sb, want_b))]
            doc, grams = np.concatenate((da, db)), np.concatenate((ga, gb))
            order = np.lexsort((grams, doc))
            doc, grams = doc[order], grams[order]
            twice = (doc[1:] == doc[:-1]) & (grams[1:] == grams[:-1])
            shared = np.bincount(doc[1:][twice], minlength=hi - lo)
            good[lo:hi] = (100 * shared >= 75 * (na + nb - shared)) & (shared > 0) & named[0] & named[1]
        take = pa.array(np.flatnonzero(good))
        yield pa.RecordBatch.from_arrays([batch.column("a").take(take), batch.column("b").take(take)], names=["a", "b"])


def _needed(x: str, y: str):
    """Grams that a linked pair shares at least: ceil(3 (n + m) / 7)."""
    return F.ceil(3 * (F.col(f"{x}n") + F.col(f"{y}n")) / F.lit(7))


def _room(x: str, y: str):
    """Grams that a pair can share if this one is the first they share."""
    return F.least(F.col(f"{x}n") - F.col(f"{x}pos"), F.col(f"{y}n") - F.col(f"{y}pos"))


def _length_fits(x: str, y: str):
    return 4 * F.least(f"{x}n", f"{y}n") >= 3 * F.greatest(f"{x}n", f"{y}n")


def _key():
    """What tells rows with a null id apart: a hash of the text; null for all other rows."""
    return F.when(F.col("doc_id").isNull(), F.xxhash64(F.coalesce("text", F.lit(""))))


def _few(df: DataFrame, size: int) -> DataFrame:
    return F.broadcast(df) if size <= BROADCAST_BYTES else df


def verify(pairs: DataFrame, reps: DataFrame, docs: DataFrame, tables: common.Scratch, tag: str) -> DataFrame:
    """(a, b) of the pairs that link; pairs: a, b (set names); reps: sig -> id of a row with that set, or its key if none has one."""
    sigs = pairs.select(F.col("a").alias("sig")).union(pairs.select(F.col("b").alias("sig"))).distinct()
    need = tables.spill(sigs.join(reps.select("sig", "id", "key"), "sig").select("sig", F.col("id").alias("rep_id"), F.col("key").alias("rep_key")), f"{tag}-need")
    n, n_keys = need.agg(F.sum(F.octet_length(F.col("rep_id").cast("string")) + 8), F.count("rep_key") * 16).first()
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    ids = _few(need.where("rep_id is not null").select("sig", "rep_id"), n or 0)
    texts = rows.join(ids, F.col("doc_id") == F.col("rep_id")).select("sig", "text")
    if n_keys:  # copies of a text have one key, so one of them is taken
        keys = _few(need.where("rep_key is not null").select("sig", "rep_key"), n_keys)
        nameless = rows.where("doc_id is null").select(_key().alias("key"), "text")
        if n_keys > BROADCAST_BYTES:
            nameless = nameless.groupBy("key").agg(F.first("text").alias("text"))
        texts = texts.union(nameless.join(keys, F.col("key") == F.col("rep_key")).groupBy("sig").agg(F.first("text").alias("text")))
    left = pairs.join(texts.select(F.col("sig").alias("a"), F.col("text").alias("text_a")), "a")
    full = left.join(texts.select(F.col("sig").alias("b"), F.col("text").alias("text_b")), "b").select("a", "b", "text_a", "text_b")
    return tables.spill(full.mapInArrow(tidy(verifier), "a bigint, b bigint").distinct(), f"{tag}-links")


def _most_shared(a: str, b: str):
    """Grams that two sets can share at most by their parts; the finer of the two is merged to the other's parts."""
    merged = lambda x: F.transform(F.sequence(F.lit(1), (F.size(x) / 2).cast("int")), lambda i: F.element_at(x, 2 * i - 1) + F.element_at(x, 2 * i))
    fit = lambda x, y: F.when(F.size(x) > F.size(y), merged(F.col(x))).otherwise(F.col(x))
    return F.aggregate(F.zip_with(fit(a, b), fit(b, a), lambda x, y: F.least(x, y)), F.lit(0), lambda s, x: s + x)


def promising(pairs: DataFrame, prefixes: DataFrame, tables: common.Scratch, tag: str) -> DataFrame:
    """(a, b) of the pairs that the prefix count and the suffix filter leave; prefixes: sig, n, grams, shape."""
    side = lambda s: prefixes.select(F.col("sig").alias(s), F.col("n").alias(f"{s}n"), F.col("grams").alias(f"{s}g"), F.col("shape").alias(f"{s}s"))
    posted = lambda s: F.col(f"{s}n") - F.floor((3 * F.col(f"{s}n") + 3) / 4) + 1
    least = F.greatest(F.lit(1), F.least(*[_needed("a", "b") - F.col(f"{s}n") + posted(s) for s in "ab"]))
    both = pairs.join(side("a"), "a").join(side("b"), "b")
    fits = (F.size(F.array_intersect("ag", "bg")) >= least) & (_most_shared("as", "bs") >= _needed("a", "b"))
    return tables.spill(both.where(fits).select("a", "b"), tag)


def _pairs_of(joined: DataFrame, x: str, y: str) -> DataFrame:
    return joined.select(F.least(f"{x}sig", f"{y}sig").alias("a"), F.greatest(f"{x}sig", f"{y}sig").alias("b")).distinct()


def classes(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row."""
    return _placed(docs).drop("least_key", "key")


def _named(rows: DataFrame, shared_names: DataFrame | None) -> DataFrame:
    """Sets that share a name get their other one."""
    if shared_names is None:
        return rows
    hit = rows.join(shared_names.select("sig", F.lit(True).alias("hit")), "sig", "left")
    return hit.withColumn("sig", F.when(F.col("hit"), F.col("other")).otherwise(F.col("sig"))).drop("hit", "other")


def _placed(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id, key, least_key) for every row; least_key: of a component of null ids alone, else null."""
    spark, tables = docs.sparkSession, common.Scratch()
    rows = docs.select("doc_id", "text")
    kind = rows.schema["doc_id"].dataType.simpleString()
    both = tables.spill(rows.withColumn("key", _key()).mapInArrow(tidy(profile), f"doc_id {kind}, key bigint, n int, sig bigint, other bigint, shape array<int>, chunk int, sums binary"), "join-profile")
    known = both.where("chunk is null").select("doc_id", "key", "n", "sig", "other", "shape")
    slots = both.where("chunk is not null").select("chunk", "sums").repartition(min(common.shuffle_width(spark), 1 << (SLOT_BITS - CHUNK_BITS)), "chunk").mapInArrow(tidy(adder), "chunk int, sums binary").collect()  # 2^SLOT_BITS sums
    counts = np.zeros(1 << SLOT_BITS, np.int64)
    for chunk, sums in slots:
        counts[chunk << CHUNK_BITS : (chunk + 1) << CHUNK_BITS] = np.frombuffer(sums, np.int64)
    rank = spark.sparkContext.broadcast(np.minimum(np.log2(counts + 1) * 1024, 65535).astype(np.uint16))

    def named_by(sets: DataFrame) -> DataFrame:
        return tables.spill(sets.where("n > 0").groupBy("sig").agg(F.min("doc_id").alias("id"), F.min("key").alias("key"), F.min("other").alias("low"), F.max("other").alias("high"), F.first("shape").alias("shape")), "join-reps")

    reps = named_by(known)
    shared_names = tables.spill(reps.where("low <> high").select("sig"), "join-names")
    if shared_names.limit(1).count():
        known = tables.spill(_named(known, shared_names).withColumn("other", F.col("sig")), "join-known")
        reps = named_by(known)
    else:
        shared_names = None
    reps = reps.select("sig", "id", F.when(F.col("id").isNull(), F.col("key")).alias("key"), "shape")

    more = shared_names is not None
    posted = _named(rows.mapInArrow(tidy(poster(rank, more)), f"gram bigint, sig bigint, n int, pos int{', other bigint' if more else ''}"), shared_names)
    chain, group = Window.partitionBy("gram").orderBy("n", "sig"), Window.partitionBy("gram")
    live = posted.select("*", F.lag(F.struct("sig", "n", "pos")).over(chain).alias("p"), (F.min("sig").over(group) != F.max("sig").over(group)).alias("shared")).where("shared").drop("shared")
    live = live.where(F.col("p").isNull() | (F.col("p.sig") != F.col("sig")))
    live = tables.spill(live.select("gram", "sig", "n", "pos", F.col("p.sig").alias("psig"), F.col("p.n").alias("pn"), F.col("p.pos").alias("ppos")), "join-live")
    prefixes = live.groupBy("sig").agg(F.first("n").alias("n"), F.collect_list("gram").alias("grams"))
    prefixes = tables.spill(prefixes.join(reps.select("sig", "shape"), "sig"), "join-prefixes")
    stars = lambda links: components(links, lambda df: tables.spill(df, "join-stars"))

    # neighbours in the order of set size
    near = _pairs_of(live.where(F.col("psig").isNotNull() & _length_fits("", "p") & (_room("", "p") >= _needed("", "p"))), "", "p")
    tried = promising(near, prefixes, tables, "join-near")
    links = verify(tried, reps, docs, tables, "join-near")
    root = stars(links)

    # long lists: each class with the list's hub, the class whose grams are the most shared
    for turn in range(HUB_ROUNDS):
        open_ = _still_open(live, root, tables)
        size = open_.groupBy("gram").agg(F.count("*").alias("c")).where(F.col("c") >= HUB_LIST)
        long_ = tables.spill(open_.join(tables.spill(size, "join-sizes"), "gram"), "join-long")
        weight = long_.groupBy("sig").agg(F.sum("c").alias("weight"))
        hub = long_.join(weight, "sig").groupBy("gram").agg(F.max(F.struct("weight", "sig", "n", "pos", "root")).alias("h"))
        hub = tables.spill(hub.select("gram", F.col("h.sig").alias("hsig"), F.col("h.n").alias("hn"), F.col("h.pos").alias("hpos"), F.col("h.root").alias("hroot")), "join-hubs")
        met = long_.join(hub, "gram").where((F.col("root") != F.col("hroot")) & _length_fits("", "h"))
        fresh = promising(_pairs_of(met, "", "h").join(tried, ["a", "b"], "left_anti"), prefixes, tables, "join-hub")
        tried = tried.union(fresh)
        links = links.union(verify(fresh, reps, docs, tables, "join-hub"))
        root = stars(links)

    # what is left: classes of different components that can share their first gram in this list
    open_ = _still_open(live, root, tables)
    side = lambda s: open_.select("gram", *[F.col(c).alias(s + c) for c in ("sig", "n", "pos", "root")])
    met = side("x").join(side("y"), "gram").where((F.col("xsig") < F.col("ysig")) & (F.col("xroot") != F.col("yroot")) & _length_fits("x", "y") & (_room("x", "y") >= _needed("x", "y")))
    far = promising(_pairs_of(met, "x", "y").join(tried, ["a", "b"], "left_anti"), prefixes, tables, "join-far")
    root = stars(links.union(verify(far, reps, docs, tables, "join-far")))

    placed = common.spill(known.join(root, F.col("sig") == F.col("node"), "left").select("doc_id", "key", "n", F.coalesce("root", "sig").alias("root")), "join-placed")
    least_id = common.spill(placed.where("n > 0").groupBy("root").agg(F.min("doc_id").alias("component_id"), F.min("key").alias("least_key")), "join-ids")
    tables.clear()
    out = placed.join(least_id, "root", "left")
    return out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"), "key", F.when((F.col("n") > 0) & F.col("component_id").isNull(), F.col("least_key")).alias("least_key"))


def _still_open(live: DataFrame, root: DataFrame, tables: common.Scratch) -> DataFrame:
    """The posting lists in which more than one component is left: gram, sig, n, pos, root."""
    named = live.select("gram", "sig", "n", "pos").join(root, F.col("sig") == F.col("node"), "left").select("gram", "sig", "n", "pos", F.coalesce("root", "sig").alias("root"))
    named = tables.spill(named, "join-named")
    several = named.groupBy("gram").agg((F.min("root") != F.max("root")).alias("several")).where("several").select("gram")
    return tables.spill(named.join(tables.spill(several, "join-several"), "gram", "left_semi"), "join-open")


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows with the smallest id of each component, columns unchanged. Rows that share that id all stay.

    Of a component of null ids alone one row stays; rows without words and id all stay. The ids that go are the fewer ones and are
    broadcast up to BROADCAST_BYTES, so that no text is shuffled; beyond, rows meet them by a shuffle.
    """
    placed = common.spill(_placed(docs), "join-keep")
    stays = F.max(F.col("doc_id") == F.col("component_id"))
    gone = common.spill(placed.where("doc_id is not null").groupBy("doc_id").agg(stays.alias("stays")).where("not stays").select("doc_id"), "join-gone")
    size = gone.agg(F.sum(F.octet_length(F.col("doc_id").cast("string")) + 8)).first()[0]
    names = docs.columns
    kept = docs.join(_few(gone, size or 0), "doc_id", "left_anti").where(docs["doc_id"].isNotNull()).select(*[docs[f"`{c}`"] for c in names])
    nameless = placed.where("component_id is null")
    if nameless.limit(1).count() == 0:
        return kept
    one = nameless.where("n_shingles > 0 and key = least_key").select("key").distinct()
    tagged = docs.where(docs["doc_id"].isNull()).select(F.struct(*[docs[f"`{c}`"] for c in names]).alias("row"), _key().alias("key"), F.coalesce("text", F.lit("")).rlike(r"[^\x20\x09-\x0D]").alias("worded"))
    first = tagged.where("worded").groupBy("key").agg(F.first("row").alias("row")).join(one, "key", "left_semi")
    return kept.unionByName(tagged.where("not worded").select("row.*")).unionByName(first.select("row.*"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(common.table(spark, sf_dir, "documents"))


ORACLE = r"""
with recursive d as (select row_number() over () as rn, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
g as (select distinct rn, doc_id, hash(array_to_string(w[p:p + least(5, len(w)) - 1], ' ')) as g from (select rn, doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) as p from d where len(w) > 0)),
n as (select rn, doc_id, count(*) as n from g group by all),
c2 as (select a.rn as x, b.rn as y, count(*) as k from g a join g b on a.g = b.g and a.rn <> b.rn group by 1, 2),
e as (select x, y from c2 join n na on na.rn = x join n nb on nb.rn = y where 100 * k >= 75 * (na.n + nb.n - k)),
reach(rn, other) as (select rn, rn from n union select r.rn, e.y from reach r join e on r.other = e.x),
c as (select r.rn, min(n.doc_id) as component_id from reach r join n on n.rn = r.other group by r.rn)
select d.doc_id, coalesce(n.n, 0)::bigint as n_shingles, coalesce(c.component_id, d.doc_id) as component_id from d left join n using (rn) left join c using (rn)
"""

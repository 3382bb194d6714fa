"""Benchmark decontamination: one Aho-Corasick automaton over the windows of all test items scans each text once.

Texts and items are normalised alike (ASCII lower case; words of letters, digits and non-ASCII bytes). Each different
word of the items has a code of two or three letters, all other words are one mark, so matches are whole words and the
automaton has two or three nodes a word instead of one a byte; a node has few branches, as they are tried in turn. Matches
are word ranges, mapped back to character offsets of the original text.

The patterns are broadcast and every worker process holds an automaton, so their size is checked: items beyond
MAX_ITEM_BYTES are dealt into blocks by id and text and the text passes the blocks' automata one after the other. Texts are never
shuffled.

Edge cases: null or wordless texts have no words and no hits; an item without words has no window; equal windows of
several items hit for all of them; repeated rows are judged one by one; an empty document table gives no rows; an empty benchmark hits nothing;
extra columns are ignored unless carried; a very long text is scanned as a whole like any other (some ten times its size in memory); the windows of an
item with a null id hit like all others, but the list of items does not name it.
"""

from __future__ import annotations

import hashlib
import sys
import types
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

common.by_value(__name__)

WINDOW = 10
#: Most bytes of item text behind one automaton (some 450 MB in each worker), and letters in a place of a code.
MAX_ITEM_BYTES, BASE = 2_000_000, 64
#: Bytes that are no part of a word, A-Z in lower case.
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 0x80 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def words_of(raw: bytes) -> list[bytes]:
    return raw.translate(_TABLE).split()


def windows_of(words: list, width: int = WINDOW) -> list[list]:
    return [words[i : i + width] for i in range(max(1, len(words) - width + 1))] if words else []


def codes_of(words) -> dict[bytes, str]:
    """Each word as letters, equally many for all: the first below BASE + 1, the others above, so codes can't overlap."""
    out, n = {}, 1
    while BASE**n < len(words):
        n += 1
    for k, word in enumerate(words):
        rest = [chr(BASE + 1 + k // BASE**i % BASE) for i in range(1, n)]
        out[word] = "".join([chr(1 + k % BASE), *rest])
    return out


def patterns_of(items: list[tuple[str | None, str]], width: int = WINDOW) -> tuple[dict[bytes, str], list[tuple[str, int, list[str]]]]:
    """(code of each item word, windows as (codes, words, ids of the items that have it))"""
    split = [(item_id, words_of((text or "").encode())) for item_id, text in items]
    codes = codes_of(dict.fromkeys(w for _, words in split for w in words))
    found: dict[str, tuple[int, set]] = {}
    for item_id, words in split:
        for w in windows_of([codes[x] for x in words], width):
            ids = found.setdefault("".join(w), (len(w), set()))[1]
            if item_id is not None:
                ids.add(item_id)
    return codes, [(w, n, sorted(ids)) for w, (n, ids) in found.items()]


def automaton_of(patterns):
    """(code of each item word, automaton over codes)"""
    import ahocorasick

    codes, windows = patterns
    out = ahocorasick.Automaton()
    for text, width, ids in windows:
        out.add_word(text, (width, ids))
    if len(out):
        out.make_automaton()
    return codes, out


def kept_automaton(key: str, patterns):
    """The worker process keeps its last automaton from task to task."""
    state = sys.modules.setdefault("_topkpaths_automaton", types.ModuleType("_topkpaths_automaton"))
    if getattr(state, "key", None) != key:
        state.key = state.automaton = None  # frees the one before
        state.automaton = automaton_of(patterns.value)
        state.key = key
    return state.automaton


def hits_in(raw: bytes, codes: dict[bytes, str], automaton) -> tuple[int, list[list[int]], list[str]]:
    """(words, merged word ranges, items)"""
    words = words_of(raw)
    if not words or not len(automaton):
        return len(words), [], []
    get = codes.get
    text = "".join([get(w, "\0") for w in words])
    found = list(automaton.iter(text))
    if not found:
        return len(words), [], []
    starts = np.flatnonzero(np.frombuffer(text.encode("latin-1"), np.uint8) <= BASE)
    last = np.searchsorted(starts, [end for end, _ in found], side="right")
    ranges = sorted({(int(j) - width, int(j)) for j, (_, (width, _)) in zip(last, found)})
    return len(words), merge(ranges), sorted({i for _, (_, ids) in found for i in ids})


def merge(ranges) -> list[list[int]]:
    out: list[list[int]] = []
    for a, b in sorted(map(tuple, ranges)):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


def char_spans(raw: bytes, ranges: list[list[int]]) -> list[list[int]]:
    """Word ranges as [start, end) in characters of the original text."""
    inside = np.frombuffer(raw.translate(_TABLE), np.uint8) != 32
    padded = np.concatenate(([False], inside, [False]))
    starts, ends = np.flatnonzero(padded[1:-1] & ~padded[:-2]), np.flatnonzero(padded[1:-1] & ~padded[2:]) + 1
    chars = np.concatenate(([0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)))
    return [[int(chars[starts[a]]), int(chars[ends[b - 1]])] for a, b in ranges]


_RANGES, _ITEMS = pa.list_(pa.list_(pa.int64())), pa.list_(pa.string())


def scanner(patterns, views, last: bool, inside: tuple[str, int] | None = None):
    """views: the kernel that gives a column's bytes; last: whether to give offsets and drop the text; inside: the struct column, and the place in it, that hold the text instead."""
    key = uuid.uuid4().hex

    def run(batches):
        codes, automaton = kept_automaton(key, patterns)
        for batch in batches:
            data, offs = views(batch.column("text") if inside is None else batch.column(inside[0]).field(inside[1]))
            n_words, ranges, items, spans = [], [], [], []
            old_r, old_i = batch.column("ranges").to_pylist(), batch.column("items").to_pylist()
            for i in range(batch.num_rows):
                raw = data[offs[i] : offs[i + 1]].tobytes()
                n, r, ids = hits_in(raw, codes, automaton)
                if old_r[i]:
                    r, ids = merge([*r, *old_r[i]]), sorted({*ids, *old_i[i]})
                n_words.append(n)
                ranges.append(r)
                items.append(ids)
                if last:
                    spans.append(char_spans(raw, r) if r else [])
            keep = [batch.column(c) for c in batch.schema.names if c not in ("text", "ranges", "items", "n_words")]
            names = [c for c in batch.schema.names if c not in ("text", "ranges", "items", "n_words")]
            mid = [] if last or inside else [batch.column("text")]
            more = [pa.array(n_words, pa.int64()), pa.array(ranges, _RANGES), pa.array(items, _ITEMS)] + ([pa.array(spans, _RANGES)] if last else [])
            yield pa.RecordBatch.from_arrays([*keep, *mid, *more], names=[*names, *(["text"] * len(mid)), "n_words", "ranges", "items", *(["spans"] * last)])

    return run


def find(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, max_bytes: int = MAX_ITEM_BYTES, carry: tuple[str, ...] = ("doc_id",), inside: tuple[str, int] | None = None) -> DataFrame:
    """Columns `carry` and n_words, ranges (of words), items, spans (of characters), one row a document.

    A carried `text` must be given under another name. inside: a carried struct, and the place in it, that hold the text, which then has no column
    of its own and goes to the workers once.
    """
    from .kernels import string_views

    spark = docs.sparkSession
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-int(total) // max_bytes))
    kept = [docs[c] for c in carry]
    fields = [f for f in docs.schema.fields if f.name in carry]
    types = {f.name: f.dataType for f in fields}
    base = ", ".join(f"`{c}` {types[c].simpleString()}" for c in carry)
    out = docs.select(*kept, *([docs["text"].alias("text")] if inside is None else []), F.lit(0).cast("long").alias("n_words"), F.array().cast("array<array<bigint>>").alias("ranges"), F.array().cast("array<string>").alias("items"))
    for k in range(blocks):
        own = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k) if blocks > 1 else items
        patterns = spark.sparkContext.broadcast(patterns_of([(r[0], r[1]) for r in own.collect()], width))
        last = k == blocks - 1
        schema = f"{base}{', ' if base else ''}{'' if last or inside else 'text string, '}n_words bigint, ranges array<array<bigint>>, items array<string>{', spans array<array<bigint>>' if last else ''}"
        out = out.mapInArrow(scanner(patterns, string_views, last, inside), schema)
    return out


def digest(found: DataFrame) -> DataFrame:
    hit = F.aggregate("ranges", F.lit(0).cast("long"), lambda s, r: s + r[1] - r[0])
    return found.select(
        "doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ",").cast("binary"), 256).alias("items_sha256"), (hit > 0).alias("contaminated"),
    )


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(find(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark")))


def brute(texts: dict, items: dict, width: int = WINDOW) -> dict:
    """The same by plain comparison, for tests."""
    out = {}
    wins = {}
    for i, t in items.items():
        w = words_of((t or "").encode())
        wins[i] = {tuple(w[p : p + width]) for p in range(max(1, len(w) - width + 1))} if w else set()
    for d, t in texts.items():
        w = words_of((t or "").encode())
        hit, ids = set(), set()
        for i, ws in wins.items():
            for x in ws:
                for p in range(len(w) - len(x) + 1):
                    if tuple(w[p : p + len(x)]) == x:
                        hit |= set(range(p, p + len(x)))
                        ids.add(str(i))
        out[d] = (len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit))
    return out


ORACLE = r"""
with d as (select row_number() over () as rn, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
b as (select item_id::varchar as item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark where item_id is not null),
bw as (select distinct item_id, least(10, len(w)) as k, array_to_string(w[p:p + least(10, len(w)) - 1], ' ') as g from (select item_id, w, unnest(range(1, greatest(len(w) - 8, 2))) as p from b where len(w) > 0)),
ks as (select distinct k from bw),
dw as (select rn, p, k, array_to_string(w[p:p + k - 1], ' ') as g from (select rn, k, w, unnest(range(1, len(w) - k + 2)) as p from d, ks where len(w) >= k)),
m as (select dw.rn, dw.p, dw.k, bw.item_id from dw join bw using (g, k)),
h as (select rn, count(distinct q) as n_hit from (select rn, unnest(range(p, p + k)) as q from (select distinct rn, p, k from m)) group by rn),
i as (select rn, count(distinct item_id) as n_items, string_agg(distinct item_id, ',' order by item_id) as ids from m group by rn)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join h using (rn) left join i using (rn)
"""

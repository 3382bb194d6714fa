"""Token-ID output as ORC: run-length encoded ids, row indexes, Bloom filters on document ids.

Texts are range-partitioned and sorted by doc_id, encoded where they lie, and written as one ORC file a range. ORC
stores the id lists with integer run-length encoding; row indexes and Bloom filters on doc_id let a reader skip stripes,
and stripes are read in parallel. `block` (the range) and `seq` (the place in it) keep the order of equal doc_ids.

Encoding: the tokenizer drops white space and no token spans it, so a text is encoded word by word, each different word
once a slice of some megabytes of texts. The different words of a slice are cut into letters and the marks around them by
one pass over the column; what is different among these is looked up in a table of bounded size, which a worker empties at the end of a task.

The number of files follows the bytes of text, FILE_BYTES each, and is no smaller than the width of shuffles.

Edge cases: a very long text is one row (an ORC row, as a text, is below 2 GB); null texts are empty and give the end id alone; null doc_ids come first; equal doc_ids keep the order of
their texts; an empty table gives empty files and no rows; extra columns are ignored.
"""

from __future__ import annotations

import json
import struct
import sys
import types
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common
from .kernels import slices, string_views, tidy

common.by_value(__name__)

TOKENIZER, END_ID = "word_bpe_49k.json", 1
#: Words whose ids are kept at a time; bytes of text encoded at a time, and behind a file, about.
TABLE_WORDS, SLICE_BYTES, FILE_BYTES = 200_000, 4_000_000, 512_000_000
ORC_OPTIONS = {"orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.create.index": "true", "orc.row.index.stride": "1000"}


def tokenizer_path(name: str) -> str:
    """A path as it is; a bare name is one of the public vocabularies."""
    if "/" in name:
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_letters() -> dict[int, str]:
    """Latin-1 letters as the characters that stand for their UTF-8 bytes in a byte-level vocabulary."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    sign = {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)}
    return {c: "".join(sign[b] for b in chr(c).encode()) for c in range(128, 256)}


class Halves(dict):
    """A table of bounded size over a function. A full half of it becomes the older half; what is found there moves to the newer one, so that what is common stays."""

    def __init__(self, made):
        self.made, self.older = made, {}

    def __missing__(self, key):
        if len(self) >= TABLE_WORDS // 2:
            self.older = dict(self)
            self.clear()
        got = self.older.get(key)
        if got is None:
            got = self.made(key)
        self[key] = got
        return got


class WordIds(Halves):
    """word -> its ids as little-endian 32-bit integers.

    A plain word (Latin-1 letters between runs of punctuation) is cut into these runs and only new runs go to the
    tokenizer's model; any other word goes through the whole tokenizer. `pooled` does this for a column of words.
    """

    MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
    LETTERS = _byte_letters()
    #: A plain word, by a pattern of the column functions: its first marks, its letters, its last marks.
    PLAIN = "^(?P<head>[{0}]*)(?P<core>[{1}]+)(?P<tail>[{0}]*)$".format("".join(f"\\x{ord(c):02x}" for c in MARKS), "".join(c for c in map(chr, range(256)) if c.isalpha()))

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__(self.ids)
        tokenizer = Tokenizer.from_file(path)
        self.encode, self.model, self.runs = tokenizer.encode, tokenizer.model, Halves(self.tokens)
        described = json.loads(tokenizer.to_str())
        # the short way is that of a lower-casing vocabulary that cuts letters from marks
        self.plain = described["model"].get("end_of_word_suffix") == "</w>" and "Lowercase" in json.dumps(described["normalizer"]) and "ByteLevel" in json.dumps(described["pre_tokenizer"])

    def tokens(self, part: str) -> bytes:
        if not part:
            return b""
        ids = [t.id for t in self.model.tokenize(part if part.isascii() else part.translate(self.LETTERS))]
        return struct.pack(f"<{len(ids)}I", *ids)

    def forget(self) -> None:
        """Empties all tables; the tokenizer stays."""
        for table in (self, self.runs):
            table.clear()
            table.older = {}

    def ids(self, word: bytes) -> bytes:
        text = word.decode("utf-8", "replace")
        tail = text.lstrip(self.MARKS)
        core = tail.rstrip(self.MARKS)
        if self.plain and core.isalpha() and (core.isascii() or max(core) <= "\xff") and "<|" not in text:
            return self.runs[text[: len(text) - len(tail)]] + self.runs[core.lower()] + self.runs[tail[len(core) :]]
        ids = self.encode(text, add_special_tokens=False).ids
        return struct.pack(f"<{len(ids)}I", *ids)


    def pooled(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words in a row, how many each has); words: different ones."""
        size, parts = len(words), []
        long = pa.types.is_large_string(words.type)
        cut = pc.extract_regex(words, self.PLAIN) if self.plain and size else pa.nulls(size, pa.struct([(x, words.type) for x in ("head", "core", "tail")]))
        plain = pc.and_(cut.is_valid(), pc.invert(pc.match_substring(words, "<|")))
        at, other = (np.flatnonzero(x.to_numpy(zero_copy_only=False)) for x in (plain, pc.invert(plain)))
        cut = cut.filter(plain)
        pools, counts, where = [], np.zeros((size, 3), np.int64), np.zeros((size, 3), np.int64)
        for k, x in enumerate(("head", "core", "tail")):
            part = cut.field(x)
            coded = (pc.utf8_lower(part) if k == 1 else part).dictionary_encode()
            parts.append((k, at, coded.indices.to_numpy(), [*map(self.runs.__getitem__, coded.dictionary.to_pylist())]))
        rest = words.filter(pc.invert(plain)).cast(pa.large_binary() if long else pa.binary()).to_pylist()
        parts.append((1, other, np.arange(len(rest)), [*map(self.__getitem__, rest)]))
        base = 0
        for k, rows, index, ids in parts:
            n = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
            counts[rows, k], where[rows, k] = n[index], (base + np.cumsum(n) - n)[index]
            pools.append(b"".join(ids))
            base += int(n.sum())
        return gathered(np.frombuffer(b"".join(pools), "<i4"), where.ravel(), counts.ravel()), counts.sum(axis=1)


def gathered(pool: np.ndarray, begins: np.ndarray, long: np.ndarray) -> np.ndarray:
    """The ranges of the pool that begin there and are so long, one behind the other."""
    ends = np.cumsum(long)
    at = np.arange(ends[-1] if len(ends) else 0)
    at += np.repeat(begins - ends + long, long)
    return pool[at]


def encoded(table: WordIds, texts: pa.Array, end: np.ndarray) -> pa.ListArray:
    """The ids of each text and the end id: each different word of the slice once, and the end of a document as one word more."""
    lists = pc.ascii_split_whitespace(texts)
    coded, upto = lists.flatten().dictionary_encode(), np.cumsum(np.diff(lists.offsets.to_numpy()))
    del lists  # a copy of the texts
    pool, sizes = table.pooled(coded.dictionary)
    pool, sizes = np.append(pool, end), np.append(sizes, 1)
    words = np.insert(coded.indices.to_numpy(), upto, len(sizes) - 1)
    del coded
    long = sizes[words]
    offsets = np.concatenate(([0], np.cumsum(long)[upto + np.arange(len(upto))])).astype(np.int32)
    begins = (np.cumsum(sizes) - sizes)[words]
    del words
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(gathered(pool, begins, long)))


def kept_table(path: str) -> WordIds:
    """The worker process keeps its tokenizer from task to task; a task leaves the table empty, as idle workers hold what they have."""
    state = sys.modules.setdefault("_topkpaths_worker_state", types.ModuleType("_topkpaths_worker_state"))
    if path not in state.__dict__:
        state.__dict__[path] = WordIds(path)
    return state.__dict__[path]


def encoder(name: str, end_id: int):
    end, views, cuts = np.array([end_id], "<u4").view("<i4"), string_views, slices

    def run(batches):
        table, seq = kept_table(tokenizer_path(name)), 0
        for batch in batches:
            texts = batch.column("text")
            for first, last in cuts(views(texts)[1], SLICE_BYTES):
                cut = batch.slice(first, last - first)
                # not kept in a name: it would stay while the next slice is encoded
                yield pa.RecordBatch.from_arrays([cut.column("doc_id"), cut.column("block"), pa.array(np.arange(seq, seq + last - first)), encoded(table, texts.slice(first, last - first), end)], names=["doc_id", "block", "seq", "tokens"])
                seq += last - first
        table.forget()

    return tidy(run)


def digester(batches):
    """n_tokens and crc32 of each list, from the columns as read."""
    for batch in batches:
        lists = batch.column("tokens")
        values = np.ascontiguousarray(lists.values.to_numpy(zero_copy_only=False), "<u4")
        offs = lists.offsets.to_numpy()
        raw = memoryview(values).cast("B")
        crc = [zlib.crc32(raw[4 * int(a) : 4 * int(b)]) for a, b in zip(offs[:-1], offs[1:])]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("block"), batch.column("seq"), pa.array(np.diff(offs).astype(np.int64)), pa.array(crc, pa.int64())], names=["doc_id", "block", "seq", "n_tokens", "ids_crc32"])


def write(docs: DataFrame, path: str, tokenizer: str = TOKENIZER, end_id: int = END_ID, files: int | None = None) -> None:
    """Writes doc_id, block, seq, tokens as ORC, in ascending doc_id."""
    if files is None:
        size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        files = max(common.shuffle_width(docs.sparkSession), -(-size // FILE_BYTES))
    id_type = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).repartitionByRange(files, F.col("doc_id").asc_nulls_first())
    rows = rows.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text").select("doc_id", "text", F.spark_partition_id().alias("block"))
    rows.mapInArrow(encoder(tokenizer, end_id), f"doc_id {id_type}, block int, seq bigint, tokens array<int>").write.options(**ORC_OPTIONS).orc(path)


def read(spark: SparkSession, path: str, id_type: str = "bigint") -> DataFrame:
    return spark.read.schema(f"doc_id {id_type}, block int, seq bigint, tokens array<int>").orc(path)


def index(stored: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of stored documents: running sums inside a block and over the few blocks."""
    id_type = stored.schema["doc_id"].dataType.simpleString()
    rows = stored.mapInArrow(tidy(digester), f"doc_id {id_type}, block int, seq bigint, n_tokens bigint, ids_crc32 bigint")
    rows = common.spill(rows, "token-index")
    inside = Window.partitionBy("block").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    blocks = rows.groupBy("block").agg(F.sum("n_tokens").alias("n"))
    blocks = blocks.select("block", F.coalesce(F.sum("n").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    rows = rows.withColumn("inside", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0)))
    return rows.join(blocks, "block").select("doc_id", (F.col("base") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")


def tokens_of(docs: DataFrame, tokenizer: str = TOKENIZER, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    path = path or common.fresh_path(spark, "tokens-orc")
    write(docs, path, tokenizer, end_id)
    return index(read(spark, path, docs.schema["doc_id"].dataType.simpleString()))


def op4_token_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens_of(common.table(spark, sf_dir, "documents"))

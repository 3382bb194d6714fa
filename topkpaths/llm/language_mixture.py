"""Language identification as a mixture: each text is a blend of languages whose shares EM estimates from letter n-grams.

Model: for each language the frequencies of hashed byte trigrams (lower case, runs of non-letters as one space), from
about MAX_DOCS training documents a language, chosen by a hash of the id with a share set by the language's full count.
Inference for each text: EM over all languages; languages with a small share go; if several remain, the nested sets of
the strongest languages are fitted again and the one with the best log likelihood less PENALTY * log(n) a language is
kept. The prediction is the language with the largest share; the score is that share.

Every language is learned. The table of a block of BLOCK languages is broadcast (256 KB a language); with more languages the
texts pass block after block, and the set chosen so far goes along with its likelihoods of the text's n-grams as candidates against the
next block. The driver holds one block and the languages' names.

Edge cases: null texts and texts without a letter are `und` with score 0; so is everything if nothing can be learned;
ties go to the language first by name; languages with a null name are not learned; repeated rows are judged alike; an empty table
gives no rows; extra columns are ignored; a very long text is a slice of its own, reduced to the counts of at most 2^BITS n-grams.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .kernels import slices, string_views

common.by_value(__name__)

#: Training documents a language, about; languages whose table is broadcast at a time, and counted at a time in a task.
MAX_DOCS, BLOCK, COUNTED = 1500, 256, 64
BITS, ROUNDS, LEAST_SHARE, PENALTY = 16, 6, 0.03, 1.0
FOLDS, HELD_OUT = 4, 2
#: A slice's bytes times languages.
_WORK = 6_000_000

_FOLD = np.full(256, 32, np.uint8)
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)
_FOLD[128:] = np.arange(128, 256)


def grams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, gram, count), sorted, of a slice; offsets from 0."""
    x = _FOLD[data]
    upper = np.zeros(len(x), bool)
    upper[1:] = (x[:-1] == 0xC3) & (x[1:] >= 0x80) & (x[1:] <= 0x9E)
    x[upper] += 0x20
    size = offsets[1:] - offsets[:-1]
    doc = np.repeat(np.arange(len(size)), size)
    keep = np.ones(len(x), bool)
    keep[1:] = (x[1:] != 32) | (x[:-1] != 32) | (doc[1:] != doc[:-1])
    x, doc = x[keep].astype(np.uint64), doc[keep]
    if len(x) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    code = (x[:-2] << np.uint64(16)) | (x[1:-1] << np.uint64(8)) | x[2:]
    code = (code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)
    inside = (doc[2:] == doc[:-2]) & (x[1:-1] != 32)
    key, count = np.unique((doc[:-2][inside] << BITS) | code[inside].astype(np.int64), return_counts=True)
    return key >> BITS, key & ((1 << BITS) - 1), count.astype(np.float32)


def counter(batches):
    """Counts of grams a language, one row a gram that occurs in the task."""
    sums: dict[str, np.ndarray] = {}

    def rows():
        for name, s in sums.items():
            at = np.flatnonzero(s)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(s[at].astype(np.int64))], names=["lang", "gram", "n"])
        sums.clear()

    for batch in batches:
        data, offs = string_views(batch.column("text"))
        lang = batch.column("lang").to_pylist()
        for lo, hi in slices(offs):
            d, g, c = grams(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo])
            for name in set(lang[lo:hi]):
                mine = np.array([x == name for x in lang[lo:hi]])[d] if len(d) else np.zeros(0, bool)
                sums.setdefault(name, np.zeros(1 << BITS))
                sums[name] += np.bincount(g[mine], weights=c[mine], minlength=1 << BITS)
            if len(sums) > COUNTED:
                yield from rows()
    yield from rows()


def train(docs: DataFrame, max_docs: int = MAX_DOCS, block: int = BLOCK) -> dict:
    """{"langs": all names, "blocks": names and frequencies (gram x language) of each block}"""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.pmod(common.crc_of_id(), F.lit(FOLDS)) != HELD_OUT)).select("doc_id", "lang", "text")
    counts = common.spill(known.groupBy("lang").agg(F.count("*").alias("n")), "language-counts")
    langs = sorted(r["lang"] for r in counts.select("lang").collect())  # one name a language
    place = F.pmod(F.xxhash64(F.lit("lang"), "doc_id"), F.lit(1 << 30)) / float(1 << 30)
    sizes = F.broadcast(counts) if len(langs) <= 10_000 else counts
    sample = known.join(sizes, "lang").where(place < F.lit(float(max_docs)) / F.col("n")).select("lang", "text")
    rows = common.spill(sample.mapInArrow(counter, "lang string, gram int, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n")), "language-grams")
    blocks = []
    for at in range(0, len(langs), block):
        names = langs[at : at + block]
        own = rows.where(F.col("lang").between(names[0], names[-1])).toArrow()  # at most a block's languages x 2^BITS
        table = np.full((1 << BITS, len(names)), 0.0)
        col = {name: k for k, name in enumerate(names)}
        np.add.at(table, (own.column("gram").to_numpy(), np.array([col[x] for x in own.column("lang").to_pylist()], np.int64)), own.column("n").to_numpy())
        table = (table + 0.05) / (table.sum(0) + 0.05 * (1 << BITS))
        blocks.append({"langs": names, "p": table.astype(np.float32)})
    return {"langs": langs, "blocks": blocks}


def em(p: np.ndarray, count: np.ndarray, doc: np.ndarray, first: np.ndarray, total: np.ndarray, allowed: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
    """Shares (document x language) and log likelihoods; allowed: the languages each document may use."""
    pi = allowed / allowed.sum(1, keepdims=True)
    pi = pi.astype(np.float32)
    for _ in range(rounds):
        w = p * pi[doc]
        s = np.maximum(w.sum(1), 1e-30)
        w *= (count / s)[:, None]
        pi = np.add.reduceat(w, first, axis=0) / total[:, None]
    s = np.maximum((p * pi[doc]).sum(1), 1e-30)
    return pi, np.add.reduceat(count * np.log(s), first)


def fit(p: np.ndarray, c: np.ndarray, doc: np.ndarray, first: np.ndarray, total: np.ndarray, allowed: np.ndarray) -> np.ndarray:
    """Shares (document x language) of the set of languages with the best penalised likelihood."""
    pi, _ = em(p, c, doc, first, total, allowed)
    k = p.shape[1]
    order = np.argsort(-pi, axis=1, kind="stable")
    strong = (pi >= LEAST_SHARE).sum(1)
    best, gain = pi.copy(), np.full(len(pi), -np.inf)
    several = np.flatnonzero(strong > 1)
    lone = np.flatnonzero(strong <= 1)
    best[lone] = 0
    best[lone, order[lone, 0]] = 1
    if len(several):  # nested sets of the strongest languages
        pick = np.isin(doc, several)
        sub_doc = np.searchsorted(several, doc[pick])
        sub_first = np.flatnonzero(np.concatenate(([True], sub_doc[1:] != sub_doc[:-1])))
        sub_p, sub_c, sub_total = p[pick], c[pick], total[several]
        rank = np.empty_like(order)
        np.put_along_axis(rank, order, np.arange(k)[None, :].repeat(len(order), 0), axis=1)
        for size in range(1, int(strong.max()) + 1):
            open_ = strong[several] >= size
            shares, ll = em(sub_p, sub_c, sub_doc, sub_first, sub_total, np.where(rank[several] < size, 1.0, 0.0))
            value = ll - PENALTY * size * np.log(sub_total + 1)
            better = open_ & (value > gain[several])
            gain[several[better]] = value[better]
            best[several[better]] = shares[better]
    return best


def infer(data: np.ndarray, offsets: np.ndarray, table: dict, carried: list) -> list:
    """For each document of a slice: [(language, share, likelihoods of its grams)] of the chosen set, None without grams.

    carried: for each document the (language, likelihoods) that earlier blocks chose; they come first, as their names do.
    """
    out: list = [None] * (len(offsets) - 1)
    d, g, c = grams(data, offsets)
    if not len(d):
        return out
    first = np.flatnonzero(np.concatenate(([True], d[1:] != d[:-1])))
    ids = d[first]
    doc = np.cumsum(np.concatenate(([0], (d[1:] != d[:-1]).astype(np.int64))))
    ends = np.append(first[1:], len(d))
    before = [carried[i] for i in ids.tolist()]
    wide = max(map(len, before), default=0)
    p = np.concatenate((np.full((len(d), wide), 1e-30, np.float32), table["p"][g]), axis=1)
    allowed = np.ones((len(ids), p.shape[1]))
    allowed[:, :wide] = 0
    for k, own in enumerate(before):
        for at, (_, like) in enumerate(own):
            p[first[k] : ends[k], at] = np.frombuffer(like, np.float32)
            allowed[k, at] = 1
    best = fit(p, c, doc, first, np.add.reduceat(c, first), allowed)
    row, col = np.nonzero(best)
    chosen: list = [[] for _ in ids]
    for r, x in zip(row.tolist(), col.tolist()):
        name = before[r][x][0] if x < wide else table["langs"][x - wide]
        chosen[r].append((name, float(best[r, x]), p[first[r] : ends[r], x]))
    for i, own in zip(ids.tolist(), chosen):
        out[i] = own
    return out


def judge(table: dict, langs: int, last: bool, with_mixture: bool = False):
    """One block's pass; langs: languages in all."""
    views, cut = string_views, slices

    def run(batches):
        import regex

        letter = regex.compile(r"\p{L}")
        for batch in batches:
            n, text = batch.num_rows, batch.column("text")
            data, offs = views(text)
            sets = [[(x["lang"], x["like"]) for x in row] for row in batch.column("chosen").to_pylist()]
            found: list = []
            for lo, hi in cut(offs, max(100_000, _WORK // len(table["langs"]))):
                found += infer(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo], table, sets[lo:hi])
            if not last:
                chosen = [[{"lang": name, "like": like.tobytes()} for name, _, like in row or []] for row in found]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), text, pa.array(chosen, _CHOSEN)], names=["doc_id", "text", "chosen"])
                continue
            names, score, mix = [], [], []
            for t, row in zip(text.to_pylist(), found):
                if t is None or letter.search(t) is None:
                    names.append("und"), score.append(0.0), mix.append([])
                elif not row:  # a letter or two: nothing to go by
                    names.append(table["first"]), score.append(1 / langs), mix.append([])
                else:
                    name, share, _ = max(row, key=lambda x: x[1])  # of equal ones the first
                    names.append(name), score.append(min(1.0, share)), mix.append([(x, s) for x, s, _ in row])
            cols = [batch.column("doc_id"), pa.array(names, pa.string()), pa.array(score, pa.float64())]
            if with_mixture:
                cols.append(pa.array(mix, pa.map_(pa.string(), pa.float64())))
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "lang_pred", "score", *["mixture"] * with_mixture])

    return run


_CHOSEN = pa.list_(pa.struct([("lang", pa.string()), ("like", pa.binary())]))


def identify(docs: DataFrame, model: dict, with_mixture: bool = False) -> DataFrame:
    """(doc_id, lang_pred, score[, mixture]) for every row."""
    rows = docs.select("doc_id", "text", F.array().cast("array<struct<lang:string,like:binary>>").alias("chosen"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    if not model["langs"]:
        mixture = [F.create_map().cast("map<string,double>").alias("mixture")] * with_mixture
        return docs.select("doc_id", F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"), *mixture)
    n_langs = len(model["langs"])
    for k, table in enumerate(model["blocks"]):
        last = k == len(model["blocks"]) - 1
        shared = docs.sparkSession.sparkContext.broadcast(table | {"first": model["langs"][0]})  # BLOCK languages x 2^BITS floats

        def run(batches, shared=shared, last=last):
            yield from judge(shared.value, n_langs, last, with_mixture)(batches)

        after = f", lang_pred string, score double{', mixture map<string,double>' * with_mixture}" if last else ", text string, chosen array<struct<lang:string,like:binary>>"
        rows = rows.mapInArrow(run, f"doc_id {kind}{after}")
    return rows


def op8_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    out = identify(docs, train(docs))
    return out.select("doc_id", (F.pmod(common.crc_of_id(), F.lit(FOLDS)) == HELD_OUT).alias("held_out"), "lang_pred", "score")

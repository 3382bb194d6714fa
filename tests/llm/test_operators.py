"""The training-data operators against plain versions on small fixtures with awkward rows."""

import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from topkpaths.llm import chat_snapshots, decontaminate, language_mixture, media_avi, ngram_join, quality_crf, queries, source_mix, substring_rlz, token_orc, url_rules

from ..helpers import duck, rows_of

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row string, gram long, block int"


def docs_of(spark, texts, lang=None, source=None):
    """Documents with extra columns whose names clash with those the operators use inside."""
    rows = [(i, t, lang(i) if lang else "en", source(i) if source else "s", len(t or ""), "x", 1, 2) for i, t in texts]
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


def awkward():
    """Nulls, empties, ties, repeats, long texts, shared passages, near copies."""
    r = random.Random(4)
    words = [f"w{i}" for i in range(400)]
    text = lambda n: " ".join(r.choice(words) for _ in range(n))
    base, passage = text(120).split(), text(60)
    out = [(0, None), (1, ""), (2, " \n\t "), (3, "one"), (4, "One"), (5, "a b c d"), (6, "to " * 300), (7, text(5000))]
    for i in range(8, 20):  # near copies of one text
        w = list(base)
        for _ in range(i % 4):
            w[r.randrange(len(w))] = f"new{i}"
        out.append((i, " ".join(w)))
    out += [(i, text(30) + " " + passage + "\n" + text(40)) for i in range(20, 28)]
    out += [(30, out[8][1]), (30, out[8][1]), (31, "é ß " * 30), (32, "\x00 a\x0bb\u00a0c"), (33, passage), (33, text(50)), (None, passage)]
    return out


def brute_rlz(texts, window=35):
    split = lambda t: [w for w in __import__("re").split(r"[\x20\x09-\x0D]+", t or "") if w]
    rows = [split(t) for _, t in texts]
    seen = Counter(tuple(w[i : i + window]) for w in rows for i in range(len(w) - window + 1))
    out = []
    for (i, _), w in zip(texts, rows):
        cut = {j for p in range(len(w) - window + 1) if seen[tuple(w[p : p + window])] > 1 for j in range(p, p + window)}
        kept = [x for j, x in enumerate(w) if j not in cut]
        out.append((i, len(w), len(cut), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


def test_substring_dedup(spark):
    texts = awkward()
    got = sorted((tuple(r) for r in substring_rlz.dedup(docs_of(spark, texts)).collect()), key=repr)
    assert got == brute_rlz(texts)
    kept = {r["doc_id"]: r["kept_text"] for r in substring_rlz.dedup(docs_of(spark, texts[:8]), with_text=True).collect()}
    assert kept[5] == "a b c d" and kept[6] == "" and kept[0] == ""


def brute_parse(keys, texts, window=35):
    """Greedy factors against each window's first place, in the order of row keys."""
    rows = [[w for w in __import__("re").split(r"[\x20\x09-\x0D]+", t or "") if w] for _, t in texts]
    places = defaultdict(set)
    for key, w in zip(keys, rows):
        for p in range(len(w) - window + 1):
            places[tuple(w[p : p + window])].add((*key, p))
    many = Counter(tuple(w[p : p + window]) for w in rows for p in range(len(w) - window + 1))
    out = []
    for (i, _), key, w in zip(texts, keys, rows):
        ref = [min(places[x]) if many[x] > 1 else None for x in (tuple(w[p : p + window]) for p in range(len(w) - window + 1))]
        p = 0
        while p < len(ref):
            if ref[p] is None:
                p += 1
                continue
            q = p
            while q + 1 < len(ref) and ref[q + 1] == (*ref[q][:2], ref[q][2] + 1):
                q += 1
            out.append((i, key[0], p, q - p + window, ref[p][0], ref[p][2]))
            p = q + window
    return sorted(out, key=repr)


def test_factors_are_the_greedy_parse(spark):
    """Copies of copies, passages with other neighbours, a passage cut by another, self-overlap."""
    r = random.Random(9)
    fresh = lambda n: [f"v{r.randrange(10**6)}" for _ in range(n)]
    a, b, c = fresh(80), fresh(70), fresh(90)
    made = [a + b, fresh(20) + b + c + fresh(9), fresh(5) + a + b + c, a[20:] + b[:50], fresh(40) + c[30:] + a[:50], ["to", "be"] * 60, a[:60] + fresh(1) + a[25:] + ["to", "be"] * 30]
    texts = [(i, " ".join(w)) for i, w in enumerate(made)] + [(3, " ".join(made[2])), (None, " ".join(c)), (None, " ".join(b + a)), (50, ""), (51, None)]
    for repeat in range(3):
        texts.append((60 + repeat, " ".join(sum((r.choice([a, b, c, fresh(30)])[r.randrange(20) : 30 + r.randrange(60)] for _ in range(6)), []))))
    docs = docs_of(spark, texts)
    key = {(x["doc_id"], x["text"]): (x["kid"], x["th"]) for x in substring_rlz.keyed(docs).collect()}
    want = brute_parse([key[i, t or ""] for i, t in texts], texts)
    assert sorted((tuple(x) for x in substring_rlz.factors(docs).collect()), key=repr) == want
    assert any(x[1] != x[4] for x in want) and any(x[3] > 85 for x in want)
    assert sorted((tuple(x) for x in substring_rlz.dedup(docs).collect()), key=repr) == brute_rlz(texts)


def test_substring_dedup_of_named_documents(spark):
    """Ids may be texts."""
    texts = [(None if i is None else f"d{i}", t) for i, t in awkward()]
    docs = spark.createDataFrame(texts, "doc_id string, text string")
    assert sorted((tuple(r) for r in substring_rlz.dedup(docs).collect()), key=repr) == brute_rlz(texts)


def brute_join(texts):
    sets = []
    for i, t in texts:
        low = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
        w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", low) if x]
        sets.append((i, {tuple(w[p : p + 5]) for p in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()))
    up = list(range(len(sets)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and 100 * len(x & y) >= 75 * len(x | y):
                up[root(a)] = root(b)
    group = defaultdict(list)
    for k, (i, s) in enumerate(sets):
        group[root(k)].append(i)
    low = {g: min([i for i in v if i is not None], default=None) for g, v in group.items()}
    return sorted(((i, len(s), low[root(k)] if s else i) for k, (i, s) in enumerate(sets)), key=repr)


def test_ngram_join(spark):
    texts = awkward()
    got = sorted((tuple(r) for r in ngram_join.classes(docs_of(spark, texts)).collect()), key=repr)
    assert got == brute_join(texts)
    kept = [r["doc_id"] for r in ngram_join.keep_one(docs_of(spark, texts)).collect()]
    low = {i: c for i, _, c in got}
    assert {i for i in kept if i is not None} == {i for i, c in low.items() if i is not None and c == i}


def test_ngram_join_rows_without_id(spark):
    """Null ids link two documents, copy one, and make a component of their own."""
    base = [f"b{i}" for i in range(100)]
    mid, far = ["x"] * 7 + base[7:], ["y"] * 7 + base[7:93] + ["z"] * 7
    bridge = base[:93] + ["z"] * 7
    alone, copy = [f"n{i}" for i in range(60)], [f"c{i}" for i in range(60)]
    texts = [(1, mid), (None, base), (None, bridge), (2, far), (None, alone), (None, alone), (None, alone[:-1] + ["q"]), (5, copy), (None, copy[:-1] + ["q"])]
    texts = [(i, " ".join(w)) for i, w in texts] + [(None, ""), (None, None), (None, "short one")]
    got = sorted((tuple(x) for x in ngram_join.classes(docs_of(spark, texts)).collect()), key=repr)
    assert got == brute_join(texts)
    kept = [(x["doc_id"], x["text"]) for x in ngram_join.keep_one(docs_of(spark, texts)).collect()]
    assert sum(i is None and t in [texts[4][1], texts[6][1]] for i, t in kept) == 1
    rest = sorted([x for x in kept if x[1] not in [texts[4][1], texts[6][1]]], key=repr)
    ids = {i for i, _, c in got if i is not None and i == c}
    assert rest == sorted([x for x in texts if x[0] in ids] + texts[-3:], key=repr)


def test_ngram_join_families(spark):
    """Families of edited copies, where neighbours by size often miss each other."""
    r = random.Random(8)
    texts = []
    for f in range(4):
        base = [f"f{f}x{r.randrange(300)}" for _ in range(90)]
        for i in range(40):
            w = list(base)
            for _ in range(r.randrange(4)):
                at = r.randrange(len(w))
                w[at : at + r.randrange(3)] = [f"n{r.random()}"] * r.randrange(1, 3)
            texts.append((len(texts), " ".join(w)))
    got = sorted((tuple(x) for x in ngram_join.classes(docs_of(spark, texts)).collect()), key=repr)
    assert got == brute_join(texts)


def test_ngram_join_of_named_documents(spark, monkeypatch):
    """Ids may be texts, and first names of sets may clash."""
    texts = [(None if i is None else f"d{i:03d}", t) for i, t in awkward()]
    docs = spark.createDataFrame(texts, "doc_id string, text string").repartition(3)
    want = brute_join(texts)
    assert sorted((tuple(x) for x in ngram_join.classes(docs).collect()), key=repr) == want
    monkeypatch.setattr(ngram_join, "NAME_BITS", 2)
    assert sorted((tuple(x) for x in ngram_join.classes(docs).collect()), key=repr) == want


def test_suffix_filter_bounds_what_sets_share(spark):
    r = random.Random(12)
    texts = [" ".join(r.choice("abcdefgh") for _ in range(r.randrange(1, 400))) for _ in range(60)]
    tables = {}
    raw = [t.encode() for t in texts]
    data, offs = np.frombuffer(b"".join(raw), np.uint8), np.concatenate(([0], np.cumsum([len(t) for t in raw])))
    doc, grams = ngram_join.sets_of(data, offs, tables)
    size = ngram_join.signatures(doc, grams, len(texts))[0]
    shape = ngram_join.shapes(doc, grams, size).to_pylist()
    sets = [set(grams[doc == i].tolist()) for i in range(len(texts))]
    assert [sum(s) for s in shape] == size.tolist() == [len(s) for s in sets]
    pairs = [(a, b) for a in range(60) for b in range(a) if 4 * min(size[a], size[b]) >= 3 * max(size[a], size[b])]
    rows = spark.createDataFrame([(a, b, shape[a], shape[b]) for a, b in pairs], "a int, b int, x array<int>, y array<int>")
    most = {(q["a"], q["b"]): q["m"] for q in rows.select("a", "b", ngram_join._most_shared("x", "y").alias("m")).collect()}
    assert all(len(sets[a] & sets[b]) <= most[a, b] <= min(size[a], size[b]) for a, b in pairs)
    assert any(most[a, b] < 0.8 * min(size[a], size[b]) for a, b in pairs)


def test_decontaminate(spark):
    r = random.Random(1)
    item = " ".join(f"Item{i}," for i in range(14))
    bench = [("7", item), ("10", "short one"), ("x", None), ("y", "..."), ("8", item)]
    texts = [(0, None), (1, ""), (2, "pre " + item.upper() + " post"), (3, "a SHORT-one! here"), (4, " ".join(f"item{i}" for i in range(9))), (5, "é" + item), (6, "w " * 3000 + item + " z" * 10), (6, "plain")]
    texts += [(i, " ".join(r.choice("abcd") for _ in range(40))) for i in range(7, 12)]
    docs, items = docs_of(spark, texts), spark.createDataFrame(bench, "item_id string, text string")
    got = sorted(tuple(x) for x in decontaminate.digest(decontaminate.find(docs, items)).collect())
    want = sorted((i, *list(decontaminate.brute({0: t}, dict(bench)).values())[0]) for i, t in texts)
    assert got == want
    small = decontaminate.digest(decontaminate.find(docs, items, max_bytes=100))  # several automata
    assert sorted(tuple(x) for x in small.collect()) == want
    spans = {x["doc_id"]: x["spans"] for x in decontaminate.find(docs, items).collect()}
    assert texts[3][1][spans[3][0][0] : spans[3][0][1]] == "SHORT-one"
    empty = decontaminate.digest(decontaminate.find(docs, items.where("false"))).collect()
    assert len(empty) == len(texts) and not any(x["contaminated"] for x in empty)


def test_decontaminate_items_without_id(spark):
    secret, known = (" ".join(f"{c}{i}" for i in range(12)) for c in "sk")
    bench = [(None, secret), (None, "two words"), ("7", known)]
    docs = docs_of(spark, [(1, "a " + secret + " b"), (2, "only two words"), (3, known + " " + secret), (4, "none of it")])
    items = spark.createDataFrame(bench, "item_id string, text string")
    for size in (decontaminate.MAX_ITEM_BYTES, 20):
        got = {x["doc_id"]: (x["n_hit"], x["n_items"], x["contaminated"]) for x in decontaminate.digest(decontaminate.find(docs, items, max_bytes=size)).collect()}
        assert got == {1: (12, 0, True), 2: (2, 0, True), 3: (24, 1, True), 4: (0, 0, False)}


def test_source_mix(spark):
    r = random.Random(2)
    texts = [(i, "w " * r.randrange(0, 60)) for i in range(400)] + [(400, None), (401, "one"), (401, "one")]
    src = lambda i: None if i % 40 == 0 else f"s{min(i % 9, 5)}" if i < 399 else "tiny"
    docs = docs_of(spark, texts, source=src)
    got = source_mix.mix(docs)
    assert rows_of(got) == duck(source_mix.ORACLE, frames={"documents": docs.toPandas()})
    rows = got.join(docs.select("doc_id", "source").distinct(), "doc_id").collect()
    taken, size, target = defaultdict(int), {}, {}
    for x in rows:
        taken[x["source"]] += x["taken"]
        size[x["source"]], target[x["source"]] = x["source_size"], x["target"]
        assert 0 <= x["taken"] <= 3 * x["size"]
    assert abs(sum(target.values()) - sum(size.values())) < 1e-6 * sum(size.values())
    assert all(target[s] <= 3 * size[s] + 1e-6 for s in target)
    assert all(abs(taken[s] - target[s]) <= 60 for s in target if s != "tiny")
    assert rows_of(got) == rows_of(source_mix.mix(docs.repartition(7)))
    made = source_mix.materialise(docs)
    assert made.columns == docs.columns and made.count() == sum(x["repeats"] for x in got.collect())


def test_token_files(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(token_orc.tokenizer_path(token_orc.TOKENIZER))
    texts = awkward() + [(40, "It's <|endoftext|> DON'T a<|startoftext|>b 12ab é\u0301 İx ﬁ"), (41, "x" * 5000)]
    got = sorted((tuple(r) for r in token_orc.tokens_of(docs_of(spark, texts)).collect()), key=lambda r: r[1])
    want, at = [], 0
    for i, x in sorted(texts, key=lambda d: (d[0] is not None, d[0] or 0, d[1] or "")):
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert got == want
    path = token_orc.common.fresh_path(spark, "t")
    token_orc.write(docs_of(spark, texts), path)
    assert token_orc.read(spark, path).where("doc_id = 7").count() == 1


def test_chat_snapshots(spark):
    rows = [(1, 0, "user", "a"), (1, 1, "bot", "b"), (2, 0, "user", "a"), (3, 0, "user", "a"), (3, 1, "bot", "b"), (4, 5, "user", "z"), (4, 6, "bot", None), (5, 0, None, "q"), (6, 0, "user", "a"), (6, 1, "bot", "c"), (7, 0, "user", "z"), (None, 0, "user", "n"), (8, 0, "u", "s"), (8, 0, "u", "s")]
    rows += [(9, i, "u", str(i)) for i in range(1200)] + [(10, i, "u", str(i)) for i in range(900)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    made = chat_snapshots.render(turns, chat_snapshots.maximal(turns)).collect()
    assert {r["conv_id"]: r["n_turns"] for r in made} == {1: 2, 4: 2, 5: 1, 6: 2, None: 1, 8: 2, 9: 1200}
    parts = sorted((r["chunk"], r["chat"]) for r in made if r["conv_id"] == 9)
    assert len(parts) == 3 and "".join(t for _, t in parts) == "".join(f"<|u|>\n{i}\n" for i in range(1200))
    none = turns.where("false")
    assert chat_snapshots.render(none, chat_snapshots.maximal(none)).count() == 0
    wide = turns.selectExpr("*", "1 as n", "2 as step", "'x' as stretch", "3 as first", "4 as k0", "5 as chunk", "6 as n_turns")
    assert sorted(map(tuple, chat_snapshots.render(wide, chat_snapshots.maximal(wide)).collect()), key=repr) == sorted(map(tuple, made), key=repr)


def test_url_rules(spark):
    urls = ["http://A.Example.com/en/7x?q#z", "https://com/en/", "ftp://net/de/", "x://example.net/de/81", "noscheme", None, "", "http://org", "http://notcom/en/", "http://x.y.org/es/#a", "http://example.com/en/", "http://com./en/", "://com/en/a://b", "http://example.comx/en/7"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)] + [(3, urls[3], "h")], "page_id long, url string, html string")
    got = url_rules.judge(pages, url_rules.rule_frame(spark, url_rules.RULES))
    assert rows_of(got) == duck(url_rules.ORACLE, frames={"pages": pages.toPandas()})
    for none in (url_rules.rule_frame(spark, ()), url_rules.rule_frame(spark, [(None, "/", "block"), ("com", None, "block")])):
        assert url_rules.judge(pages, none).where("verdict = 'allow' and rule is null").count() == len(urls) + 1
    assert url_rules.judge(pages.where("false"), url_rules.rule_frame(spark, url_rules.RULES)).count() == 0


def test_url_rules_of_the_contract(spark):
    """The registered rules' words, one by one: net/de/ allows, and only its longer rule blocks; the SQL agrees."""
    urls = {"h://com/en/1": ("com/en/", "block"), "h://a.example.com/en/7": ("example.com/en/7", "allow"), "h://example.net/de/7": ("net/de/", "allow"), "h://example.net/de/8": ("example.net/de/8", "block"), "h://org/es/": ("org/es/", "block")}
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    found = url_rules.judge(pages, url_rules.rule_frame(spark, url_rules.RULES))
    assert [tuple(r) for r in found.orderBy("page_id").select("rule", "verdict").collect()] == list(urls.values())
    assert rows_of(found) == duck(url_rules.ORACLE, frames={"pages": pages.toPandas()})


def test_url_rules_nested(spark):
    """Deep nests, rules of one host in each other, ties, hot urls, borders in other ranges than their urls; columns that clash."""
    r = random.Random(6)
    hosts = ["com", "a.com", "b.a.com", "net", "x.net", "c.b.a.com", "", "."]
    path = lambda: "".join(r.choice(["/", "a", "b", "é"]) for _ in range(r.randrange(6)))
    rules = [(r.choice(hosts), p if r.random() < 0.2 else "/" + p, r.choice(["allow", "block"])) for p in (path() for _ in range(80))]
    rules += [("com", "/" + "a" * i, "block") for i in range(8)] + [("com", "", "allow"), ("com", "a", "block"), ("c/d", "", "block")]
    urls = [f"h://{r.choice(['', 'z.', 'y.z.'])}{r.choice(hosts)}/{path()}" for _ in range(300)] + ["h://a.com/ab"] * 40 + ["h://com", "h://xcom/a", "h://" + "d." * 50 + "com/a", None]
    pages = spark.createDataFrame([(i // 2, u, "at", 1, 2, "r") for i, u in enumerate(urls)], "page_id long, url string, at string, step int, row int, rule string").repartition(4)

    def plain(url):
        rest = (url or "").split("://", 1)[1] if "://" in (url or "") else ""
        host = __import__("re").match(r"[^/?#]*", rest)[0]
        path = __import__("re").match(r"[^?#]*", rest[len(host) :])[0]
        fits = [(-len(h + p), -len(h), v, h + p) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return (host, path, *((min(fits)[3], min(fits)[2]) if fits else (None, "allow")))

    want = sorted(((i // 2, *plain(u)) for i, u in enumerate(urls)), key=repr)
    table = spark.createDataFrame(rules, "host string, path string, verdict string")
    for ranges in (1, 3, 40):
        assert sorted(map(tuple, url_rules.judge(pages, table, ranges=ranges).collect()), key=repr) == want


def test_media_round_trip(spark):
    texts = awkward()
    got = {(r["doc_id"], r["n_bytes"], r["payload_sha256"]): r for r in media_avi.measure(media_avi.store(docs_of(spark, texts))).collect()}
    for i, t in texts:
        raw = (t or "").encode()
        pad = media_avi.padded(raw)
        r = got[i, len(raw), hashlib.sha256(pad).hexdigest()]
        assert r["payload_bytes"] == len(pad) and r["tail_crc32"] == zlib.crc32(pad[-64:]) and len(pad) % 64 == 0
    clips = media_avi.clips(media_avi.store(docs_of(spark, texts))).where("doc_id = 7").orderBy("clip").collect()
    assert clips[0]["start_s"] == 0 and all(a["end_s"] == b["start_s"] for a, b in zip(clips, clips[1:]))


def test_media_decoder():
    """The general decoder agrees with the fast one, finds frames without an index, and shots at planted cuts."""
    rnd = np.random.default_rng(1)
    samples = rnd.integers(0, 256, 64 * 2, dtype=np.uint8)
    raw = media_avi.encode_frame(samples, media_avi.jpeg_head(2, 64))
    fast, full = media_avi.decode_frame(raw), media_avi.decode_planes(raw)[0]
    assert (fast.ravel() == samples).all() and (full[::8, ::8] == fast).all() and (full[3::8, 5::8] == fast).all()
    film = bytes([10] * 64 * 32 * 5 + [200] * 64 * 32 * 4)
    avi = media_avi.write_avi(film)
    assert [s[:2] for s in media_avi.shots_of(media_avi.read_payload(avi)[1])] == [(0, 5), (5, 4)]
    cut = avi[: avi.rfind(b"idx1")]
    assert media_avi.read_payload(cut)[0] == film and media_avi.parse_avi(b"no avi")["frames"] == []


def jpeg_of(planes, sampling, restart=0, apart=False, tables=False):
    """A baseline JPEG of planes at their own sizes, coded symbol by symbol with the standard's tables."""
    book = {}
    for name, (counts, values) in media_avi._STANDARD.items():
        code, k = 0, 0
        for length, n in enumerate(counts, 1):
            for _ in range(n):
                book[name, values[k]] = f"{code:0{length}b}"
                code, k = code + 1, k + 1
            code <<= 1

    def amount(v):
        n = abs(v).bit_length()
        return n, f"{v if v > 0 else v + (1 << n) - 1:0{n}b}" if n else ""

    def block(part, y, x, level):
        cells = media_avi._COS @ (planes[part][8 * y : 8 * y + 8, 8 * x : 8 * x + 8].astype(float) - 128) @ media_avi._COS.T
        z = np.rint(cells.ravel()[media_avi.ZIGZAG] / 2).astype(int).tolist()
        chroma = int(part > 0)
        n, tail = amount(z[0] - level[part])
        level[part], out, run = z[0], book[chroma, n] + tail, 0
        last = max([k for k in range(1, 64) if z[k]], default=0)
        for k in range(1, last + 1):
            if not z[k]:
                run += 1
                continue
            out += book[16 | chroma, 0xF0] * (run // 16)
            n, tail = amount(z[k])
            out, run = out + book[16 | chroma, run % 16 << 4 | n] + tail, 0
        return out + (book[16 | chroma, 0] if last < 63 else "")

    def coded(steps):
        out, level = b"", [0] * len(planes)
        groups = [steps[i : i + restart] for i in range(0, len(steps), restart)] if restart else [steps]
        for k, group in enumerate(groups):
            bits = "".join(block(*b, level) for step in group for b in step)
            bits += "1" * (-len(bits) % 8)
            out += int(bits, 2).to_bytes(len(bits) // 8, "big").replace(b"\xff", b"\xff\x00") if bits else b""
            if k < len(groups) - 1:
                out, level = out + bytes([0xFF, 0xD0 + k % 8]), [0] * len(planes)
        return out

    seg = media_avi._segment
    rows, cols = planes[0].shape
    raw = b"\xff\xd8" + seg(0xDB, b"\0" + bytes([2] * 64)) + seg(0xC0, media_avi.struct.pack(">BHHB", 8, rows, cols, len(planes)) + b"".join(bytes([i + 1, s[0] << 4 | s[1], 0]) for i, s in enumerate(sampling)))
    raw += b"".join(seg(0xC4, bytes([n]) + c + v) for n, (c, v) in media_avi._STANDARD.items()) if tables else b""
    raw += seg(0xDD, media_avi.struct.pack(">H", restart)) if restart else b""
    scans = [[i] for i in range(len(planes))] if apart else [list(range(len(planes)))]
    for scan in scans:
        raw += seg(0xDA, bytes([len(scan)]) + b"".join(bytes([i + 1, 0x11 if i else 0]) for i in scan) + bytes([0, 63, 0]))
        if len(scan) == 1:
            h, w = (x // 8 for x in planes[scan[0]].shape)
            raw += coded([[(scan[0], y, x)] for y in range(h) for x in range(w)])
        else:
            h, w = rows // (8 * sampling[0][1]), cols // (8 * sampling[0][0])
            raw += coded([[(i, v * sampling[i][1] + y, u * sampling[i][0] + x) for i in scan for y in range(sampling[i][1]) for x in range(sampling[i][0])] for v in range(h) for u in range(w)])
    return raw + b"\xff\xd9"


@pytest.mark.parametrize("sampling", [[(1, 1)], [(1, 1), (1, 1), (1, 1)], [(2, 2), (1, 1), (1, 1)], [(2, 1), (1, 1), (1, 1)]])
@pytest.mark.parametrize("more", [{}, {"restart": 3}, {"apart": True}, {"tables": True, "restart": 1}])
def test_colour_frames(sampling, more):
    rnd = np.random.default_rng(3)
    wide, high = sampling[0]
    smooth = lambda h, w: np.clip(np.add.outer(np.arange(h) * 3, np.arange(w) * 2) % 200 + rnd.integers(0, 40, (h, w)), 0, 255).astype(np.uint8)
    planes = [smooth(32, 48), *[smooth(32 // high, 48 // wide) for _ in sampling[1:]]]
    got = media_avi.decode_planes(jpeg_of(planes, sampling, **more))
    for p, g in zip(planes, got):
        full = np.repeat(np.repeat(p, 32 // p.shape[0], 0), 48 // p.shape[1], 1)
        assert g.shape == (32, 48) and np.abs(g.astype(int) - full).max() <= 8


def test_unreadable_media(spark):
    """A colour film behind an OpenDML index, in two RIFF parts; and everything that has no clips gives its reason."""
    rnd = np.random.default_rng(5)
    dark, light = (jpeg_of([np.clip(rnd.integers(0, 20, (16, 16)) + v, 0, 255).astype(np.uint8), *[np.full((8, 8), 128, np.uint8)] * 2], [(2, 2), (1, 1), (1, 1)]) for v in (20, 200))
    pack, chunk, list_ = media_avi.struct.pack, media_avi._chunk, media_avi._list

    def film(frames, cut):
        head = list_(b"hdrl", chunk(b"avih", pack("<I", 40_000) + bytes(52)) + list_(b"strl", chunk(b"strh", b"auds" + bytes(52))) + list_(b"strl", chunk(b"strh", b"vidsMJPG" + bytes(48)) + chunk(b"indx", bytes(24 + 32))))
        parts, out = [frames[:cut], frames[cut:]], b""
        index = []
        for k, part in enumerate(parts):
            start = len(out) + 12 + (len(head) if not k else 0) + 12
            movi, rows = chunk(b"00wb", b"sound"), []
            for f in part:
                rows.append((start + len(movi) + 8, len(f)))
                movi += chunk(b"01dc", f)
            index.append((start + len(movi), len(rows)))
            movi += chunk(b"ix01", pack("<HBBI4sQI", 2, 0, 1, len(rows), b"01dc", start, 0) + b"".join(pack("<II", a - start, n) for a, n in rows))
            body = (b"AVI " + head if not k else b"AVIX") + list_(b"movi", movi)
            out += b"RIFF" + pack("<I", len(body)) + body
        whole = chunk(b"indx", pack("<HBBI4s12x", 4, 0, 0, 2, b"01dc") + b"".join(pack("<QII", a, 0, n) for a, n in index))
        return out.replace(chunk(b"indx", bytes(24 + 32)), whole)

    good = film([dark] * 5 + [b""] + [light] * 4, 6)
    assert [s["first_frame"] for s in media_avi.clips_of(good)[0]] == [0, 6]
    assert media_avi.parse_avi(good)["rate"] == 25 and len(media_avi.parse_avi(good)["frames"]) == 10
    plain = media_avi.write_avi(bytes(range(64)))
    bad = {1: None, 2: b"", 3: b"RIFF....WAVE", 4: b"RIFF\0\0\0\0AVI ", 5: plain[:-40].replace(b"\xff\xc0", b"\xff\xc2"), 6: good, 7: plain.replace(b"\xff\xd8", b"\x00\x00")}
    rows = media_avi.clips(spark.createDataFrame(list(bad.items()), "doc_id int, media binary")).collect()
    why = {r["doc_id"]: r["reason"] for r in rows}
    assert why == {1: "null", 2: "no AVI", 3: "no AVI", 4: "no frames", 5: "not a baseline JPEG", 6: None, 7: "no JPEG frame"}
    assert [r["clip"] for r in rows if r["doc_id"] == 6] == [0, 1]


def labelled(spark, n=400):
    r = random.Random(3)
    good = lambda: ". ".join(" ".join(r.choice(["the", "cat", "sat", "down", "there", "again"]) for _ in range(8)) for _ in range(3)) + "."
    bad = lambda: " ".join(r.choice(["BUY!!", "###", "$$$", "now!!", "||"]) for _ in range(20))
    texts = [(i, "\n".join((good if i % 3 else bad)() for _ in range(r.randrange(1, 9)))) for i in range(n)]
    return texts, spark.createDataFrame([(i, int(i % 3 > 0), 0) for i in range(n)], "doc_id long, quality int, toxic int")


def test_quality_field(spark):
    texts, labels = labelled(spark)
    docs = docs_of(spark, texts + [(900, None), (901, ""), (902, "\n\n")])
    model = quality_crf.train(docs, labels)
    score = {r["doc_id"]: r["score"] for r in quality_crf.score(docs, model).collect()}
    held = [i for i, _ in texts if zlib.crc32(str(i).encode()) % 5 == 0]
    assert sum((score[i] >= 0.3) == (i % 3 > 0) for i in held) >= 0.97 * len(held)
    assert all(0 <= s <= 1 for s in score.values()) and score[900] == score[901] == score[902] == 0.5
    kept = quality_crf.keep_good(docs, model)
    assert kept.columns == docs.columns
    assert quality_crf.score(docs, quality_crf.train(docs, labels.where("false"))).where("score <> 0.5").count() == 0
    assert quality_crf.label_lines(docs.where("doc_id < 3"), model).where("size > 0").count() > 0


def plain_quality(text, model):
    """The score of one text, line by line and by a sum over labellings kept as a small table."""
    space, upper, lower = set(b" \t\n\x0b\x0c\r"), range(65, 91), [*range(97, 123), *range(0xC3, 0xF5)]
    rows = []
    for line in __import__("re").split(rb"[\n\r]", (text or "").encode()):
        words = [w for w in __import__("re").split(rb"[\x20\x09-\x0D]+", line) if w]
        if not words:
            continue
        count = lambda members: sum(c in members for c in line)
        accents = sum(a == 0xC3 and 0x80 <= b <= 0x9E for a, b in zip(line, line[1:]))
        up, n, size = count(upper) + accents, len(words), sum(c not in space for c in line)
        capital = up / max(up + count(lower), 1)
        symbols, bars, shouts, digits = (count(m) / n for m in (b"#$%&*~^_=<>@\\+{}[]", b"|", b"!", range(48, 58)))
        again = sum(a == b for a, b in zip(words, words[1:])) / n
        flags = [n == 1, words[-1][-1] in b".?!:;\"')", capital > 0.6, symbols > 0.3, bars > 0.3, shouts > 0.3, again > 0.3, size / n > 15]
        rows.append(([1, capital, min(symbols, 3), min(bars, 1), min(shouts, 2), min(digits, 3), again, min(size / n, 30) / 10, np.log1p(size) / 10, *flags], size))
    if not rows:
        return model["empty"]
    zero, t = [0] * 17, model["t"]
    u = []
    for k, (f, _) in enumerate(rows):
        first, last = k == 0, k == len(rows) - 1
        x = [*f, *(zero if first else rows[k - 1][0]), *(zero if last else rows[k + 1][0]), first, last, first and last]
        u.append(np.dot(x, model["w"]) + model["bias"])
    total, good = 0.0, np.zeros(len(u))
    for m in range(1 << len(u)):
        y = [(m >> i) & 1 for i in range(len(u))]
        w = np.exp(sum(a for a, b in zip(u, y) if b) + model["start"] * y[0] + sum(t[a][b] for a, b in zip(y, y[1:])))
        total += w
        good += w * np.array(y)
    size = np.array([s for _, s in rows])
    return float((size * good / total).sum() / size.sum())


def test_quality_scores_against_plain_ones(spark):
    texts, labels = labelled(spark, 200)
    rows = texts[:40] + [(300, None), (301, ""), (302, "ÉA b\r\n\n x|| !! 12\n" * 3), (303, "a a a b! <#> " * 9), (303, "ok."), (None, "No id."), (304, " \x0b one\n")]
    model = quality_crf.train(docs_of(spark, texts), labels)
    got = sorted(((r["doc_id"], r["score"]) for r in quality_crf.score(docs_of(spark, rows), model).collect()), key=repr)
    want = sorted(((i, plain_quality(t, model)) for i, t in rows), key=repr)
    assert [i for i, _ in got] == [i for i, _ in want]
    assert np.allclose([s for _, s in got], [s for _, s in want], atol=1e-4)
    few = quality_crf.train(docs_of(spark, texts), labels, max_lines=300)
    assert "w" in few and quality_crf.train(docs_of(spark, texts), labels, max_lines=0) == {"empty": 0.5}
    empty = docs_of(spark, rows).where("false")
    assert quality_crf.score(empty, model).count() == quality_crf.keep_good(empty, model).count() == 0
    assert quality_crf.train(empty, labels) == {"empty": 0.5}


def test_field_marginals_are_exact():
    """Forward-backward against a sum over all labellings."""
    rnd = np.random.default_rng(0)
    u, t, s = rnd.normal(size=5), rnd.normal(size=(2, 2)), 0.3
    a, b = quality_crf.forward_backward(u, quality_crf.Chains(np.zeros(5, int)), t, s)
    total, one = 0.0, np.zeros(5)
    for m in range(32):
        y = [(m >> i) & 1 for i in range(5)]
        w = np.exp(sum(u[i] * y[i] for i in range(5)) + s * y[0] + sum(t[y[i], y[i + 1]] for i in range(4)))
        total += w
        one += w * np.array(y)
    assert np.allclose(1 / (1 + np.exp(-(a + b))), one / total)


def test_language_mixture(spark):
    r = random.Random(5)
    vocab = {"en": "the of and which that house water tree".split(), "de": "der und nicht haus wasser baum für über".split(), "fr": "le la est maison eau arbre été où".split()}
    langs = ["en", "de", "fr"]
    texts = [(i, " ".join(r.choice(vocab[langs[i % 3]]) for _ in range(30))) for i in range(240)]
    half = " ".join(r.choice(vocab["en"]) for _ in range(60)) + " " + " ".join(r.choice(vocab["fr"]) for _ in range(30))
    texts += [(500, None), (501, ""), (502, "123 ... !"), (503, half), (504, "é")]
    docs = docs_of(spark, texts, lang=lambda i: langs[i % 3] if i < 240 else None)
    model = language_mixture.train(docs)
    got = {x["doc_id"]: x for x in language_mixture.identify(docs, model, with_mixture=True).collect()}
    assert sum(got[i]["lang_pred"] == langs[i % 3] for i in range(240)) >= 236
    assert [got[i]["lang_pred"] for i in (500, 501, 502)] == ["und"] * 3 and got[504]["lang_pred"] in langs
    assert set(got[503]["mixture"]) == {"en", "fr"} and got[503]["lang_pred"] == "en" and 0.5 < got[503]["score"] < 0.85
    none = language_mixture.identify(docs, language_mixture.train(docs.where("false"))).select("lang_pred").distinct().collect()
    assert [x[0] for x in none] == ["und"]


def plain_mixture(text, table, langs):
    """Shares by EM over plain dictionaries."""
    codes = []
    for b in (text or "").encode():
        c = b + 32 if 65 <= b <= 90 else b if b >= 128 or 97 <= b <= 122 else 32
        if codes and codes[-1] == 0xC3 and 0x80 <= c <= 0x9E:
            c += 32
        if c != 32 or not codes or codes[-1] != 32:
            codes.append(c)
    count = Counter()
    for x, y, z in zip(codes, codes[1:], codes[2:]):
        if y != 32:
            count[((x << 16 | y << 8 | z) * 0x9E3779B97F4A7C15 % 2**64) >> (64 - language_mixture.BITS)] += 1
    total = sum(count.values())
    if not total:
        return None

    def em(allowed):
        pi = {k: 1 / len(allowed) for k in allowed}
        for _ in range(language_mixture.ROUNDS):
            new = dict.fromkeys(allowed, 0.0)
            for g, c in count.items():
                s = sum(pi[k] * table[g, k] for k in allowed)
                for k in allowed:
                    new[k] += c * pi[k] * table[g, k] / s / total
            pi = new
        return pi, sum(c * np.log(sum(pi[k] * table[g, k] for k in allowed)) for g, c in count.items())

    pi, _ = em(range(len(langs)))
    order = sorted(pi, key=lambda k: -pi[k])
    strong = sum(v >= language_mixture.LEAST_SHARE for v in pi.values())
    if strong <= 1:
        return {langs[order[0]]: 1.0}
    fits = [em(sorted(order[:n])) for n in range(1, strong + 1)]
    values = [ll - language_mixture.PENALTY * n * np.log(total + 1) for n, (_, ll) in enumerate(fits, 1)]
    return {langs[k]: v for k, v in fits[values.index(max(values))][0].items()}


def test_mixtures_against_plain_ones(spark):
    """EM and the choice of the set, one block of languages and several."""
    r = random.Random(7)
    vocab = {"en": "the of and which that house water tree".split(), "de": "der und nicht haus wasser baum für über".split(), "fr": "le la est maison eau arbre été où".split(), "xx": "zog kruv zilp mork trum vosk glim".split()}
    langs = sorted(vocab)
    texts = [(i, " ".join(r.choice(vocab[langs[i % 4]]) for _ in range(30))) for i in range(160)]
    mixed = [(i, " ".join(r.choice(vocab[r.choice(two)]) for _ in range(r.randrange(1, 80)))) for i, two in enumerate([r.sample(langs, r.randrange(1, 4)) for _ in range(40)], 200)]
    mixed += [(300, "ÉTÉ où"), (301, None), (302, "é"), (303, "a" * 3000), (303, "12"), (None, "water")]
    docs = docs_of(spark, texts, lang=lambda i: langs[i % 4])
    model = language_mixture.train(docs)
    table = model["blocks"][0]["p"].astype(float)
    ask = docs_of(spark, mixed)
    got = sorted(((x["doc_id"], x["lang_pred"], x["score"], x["mixture"]) for x in language_mixture.identify(ask, model, with_mixture=True).collect()), key=repr)
    for (i, pred, score, mix), (j, t) in zip(got, sorted(mixed, key=lambda m: repr((m[0], next(x[1] for x in got if x[0] == m[0]))))):
        assert i == j
        if i == 303:
            continue
        want = plain_mixture(t, table, langs)
        if want is None:
            assert mix == {} and pred == ("und" if not t else langs[0])
            continue
        assert set(mix) == {k for k, v in want.items() if v > 0} and all(abs(mix[k] - want[k]) < 1e-3 for k in mix)
        assert abs(score - max(want.values())) < 1e-3 and abs(want[pred] - max(want.values())) < 1e-3
    parts = language_mixture.train(docs, block=3)
    assert [b["langs"] for b in parts["blocks"]] == [langs[:3], langs[3:]]
    again = {x["doc_id"]: x["lang_pred"] for x in language_mixture.identify(ask.where("doc_id < 300"), parts).collect()}
    assert sum(again[i] == pred for i, pred, _, _ in got if i is not None and i < 300) >= 38
    assert language_mixture.identify(ask.where("false"), parts).count() == 0


def test_stripes_are_skipped(spark):
    """A reader that asks for one document gets no more than a stretch of rows from the scan."""
    docs = spark.range(12_000).selectExpr("id as doc_id", "concat('some text of ', id) as text")
    path = token_orc.common.fresh_path(spark, "pruned")
    token_orc.write(docs, path, files=2)
    for wanted, most in ((7_777, 1000), (99_999, 0)):
        one = token_orc.read(spark, path).where(f"doc_id = {wanted}")
        assert one.count() == min(most, 1)
        one = one.select("doc_id", "tokens")
        leaves = one._jdf.queryExecution().executedPlan()
        rows = one._jdf.queryExecution().toRdd().count()
        scan = leaves.collectLeaves().apply(0)
        assert rows == min(most, 1) and scan.metrics().apply("numOutputRows").value() <= most


def test_token_table_keeps_common_words(monkeypatch):
    """A word met again and again is encoded once, however many other words pass through the bounded table; ids stay the tokenizer's in slices of any size."""
    import pyarrow as pa
    from tokenizers import Tokenizer

    path = token_orc.tokenizer_path(token_orc.TOKENIZER)
    whole, table, seen = Tokenizer.from_file(path), token_orc.WordIds(path), []
    model = table.model
    table.model = type("Counted", (), {"tokenize": staticmethod(lambda part: seen.append(part) or model.tokenize(part))})
    monkeypatch.setattr(token_orc, "TABLE_WORDS", 20)
    r = random.Random(2)
    for _ in range(200):
        for word in ("common", "".join(r.choice("abcdefgh") for _ in range(9))):
            assert list(memoryview(table[word.encode()]).cast("I")) == whole.encode(word, add_special_tokens=False).ids
    assert seen.count("common") == 1
    texts = ["", " ", "a\x0bb\x0c c ", "É ß <|x|> !!!Hi!!! \x00z", "common words\x1cand\u00a0more"] * 3
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(len(texts))), "block": pa.array([0] * len(texts), pa.int32()), "text": texts})
    for size in (1, 30, 4_000_000):
        monkeypatch.setattr(token_orc, "SLICE_BYTES", size)
        got = pa.Table.from_batches(list(token_orc.encoder(path, 1)([batch, batch.slice(4)])))
        assert got["tokens"].to_pylist() == [[*whole.encode(t, add_special_tokens=False).ids, 1] for t in texts + texts[4:]] and got["seq"].to_pylist() == list(range(len(texts) * 2 - 4))


def test_keep_one_shuffles_no_texts(spark, monkeypatch):
    """The ids that go are broadcast while they are few; a shuffle beyond that keeps the same rows, repeated and null ids included."""
    words = [" ".join(f"w{k}x{i}" for i in range(60)) for k in range(4)]
    texts = [(1, words[0]), (2, words[0] + " more"), (3, words[1]), (3, words[0]), (4, words[2]), (5, words[1]), (None, words[1]), (None, words[3]), (None, words[3]), (6, ""), (6, None), (None, "")]
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        kept, most = [], ngram_join.BROADCAST_BYTES
        for size in (most, 0):
            monkeypatch.setattr(ngram_join, "BROADCAST_BYTES", size)
            out = ngram_join.keep_one(docs_of(spark, texts))
            kept.append(sorted(map(str, out.select("doc_id", "text").collect())))
            anti = [x for x in out._jdf.queryExecution().sparkPlan().toString().split("\n") if "LeftAnti" in x]
            assert len(anti) == 1 and ("BroadcastHashJoin" in anti[0]) == (size > 0)
        want = [texts[0], texts[2], texts[3], texts[4], texts[7], texts[9], texts[10], texts[11]]
        assert kept[0] == kept[1] == sorted(str(r) for r in docs_of(spark, want).select("doc_id", "text").collect())
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_plain_words_are_cut_by_columns():
    """Letters and marks are looked up, not each different word, and a task leaves nothing behind; odd words, letters beyond ASCII and marks that stand for a token get the tokenizer's ids."""
    import pyarrow as pa
    from tokenizers import Tokenizer

    path = token_orc.tokenizer_path(token_orc.TOKENIZER)
    whole, r = Tokenizer.from_file(path), random.Random(5)
    letters = "aBzÀéßÿµªº×÷ĀıſK1٣-'’\u0301\x00<|>[]^\\.,()"
    texts = ["Bzab, bzab. (bzab) BZAB", *(" ".join("".join(r.choice(letters) for _ in range(r.randrange(1, 7))) for _ in range(40)) for _ in range(60))]
    kept, seen = token_orc.kept_table(path), []
    kept.made = lambda word: seen.append(word) or kept.ids(word)
    for kind in (pa.string(), pa.large_string()):
        batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array([0] * len(texts), pa.int32()), pa.array(texts, kind)], names=["doc_id", "block", "text"])
        got = pa.Table.from_batches(list(token_orc.encoder(path, 1)([batch])))
        assert got["tokens"].to_pylist() == [[*whole.encode(t, add_special_tokens=False).ids, 1] for t in texts]
        assert not (kept or kept.older or kept.runs or kept.runs.older)
    assert seen and not {b"Bzab,", b"bzab.", b"(bzab)", b"BZAB"} & set(seen)


def test_tasks_hand_back_memory(monkeypatch):
    """What a task freed goes back to the system at its end, though blocks still in use lie behind it; the token kernel does so once a task."""
    import ctypes
    import re

    import pyarrow as pa
    from topkpaths.llm import kernels

    if not hasattr(ctypes.CDLL(None), "malloc_trim"):
        pytest.skip("not glibc")
    left = []

    def held():
        with open("/proc/self/status") as f:
            return int(re.search(r"RssAnon:\s+(\d+)", f.read())[1]) // 1024

    def wasteful(batches):
        for batch in batches:
            blocks = [b"x" * (1000 + i % 2) for i in range(100_000)]
            left.append(blocks[-1])
            yield batch
            del blocks

    assert list(wasteful([1])) == [1]
    before = held()
    assert list(kernels.tidy(wasteful)([1, 2])) == [1, 2] and held() < before - 50
    calls = []
    monkeypatch.setattr(kernels, "hand_back", lambda: calls.append(1))
    path = token_orc.tokenizer_path(token_orc.TOKENIZER)
    batch = pa.RecordBatch.from_pydict({"doc_id": [1], "block": pa.array([0], pa.int32()), "text": ["a b"]})
    assert len(list(token_orc.encoder(path, 1)([batch, batch]))) == 2 and calls == [1]


@pytest.mark.parametrize("name", ["op3_source_mix", "op5_chat_snapshots", "op7_decontaminate", "op9_url_rules", "op2_substring_rlz", "op6_ngram_join"])
def test_query_against_sql(spark, sf, name):
    assert rows_of(queries.QUERIES[name](spark, sf)) == duck(queries.ORACLES[name], sf)


def test_empty_tables(spark):
    docs = docs_of(spark, [(1, "x")]).where("false")
    assert decontaminate.digest(decontaminate.find(docs, spark.createDataFrame([("1", "x")], "item_id string, text string"))).count() == 0
    for f in (substring_rlz.dedup, ngram_join.classes, source_mix.mix, token_orc.tokens_of, lambda d: media_avi.measure(media_avi.store(d))):
        assert f(docs).count() == 0

"""The ten text operators against brute force, and on rows that are hard to handle."""

import hashlib
import math
import re
import time
import zlib
from collections import Counter, defaultdict
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from twigmine.llm import bpe, exact, fingerprints, html, katz, licences, mixing, near, quality, queries, warc
from twigmine.llm.common import hashed_words
from twigmine.llm.components import components

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
#: Nulls, empty and very long texts, ties, repeated rows.
ODD = [
    (1, None, None, None, None), (2, "", "en", "a", 0), (3, " \n\t ", "en", "a", 3), (4, "Same TEXT here", "en", "a", 1), (5, "same text HERE", "en", "b", 1),
    (6, "word " * 40_000, "en", "b", 1), (7, "word " * 40_000, "en", "b", 1), (8, "É ü 漢字 😀 <|endoftext|> x", None, "c", 1), (9, "one two three four five six seven eight nine ten", "en", "c", 1),
    (9, "one two three four five six seven eight nine ten", "en", "c", 1), (10, "a", "en", "", 1), (None, "no id", "en", "a", 1), (12, "one two three four five six seven eight nine eleven", "en", "c", 1),
]


def docs_of(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    """With further columns whose names clash with those the operators use inside."""
    return docs_of(spark, ODD).withColumns({c: F.lit("x") for c in ("digest", "kept", "n", "p", "t", "tokens", "h", "run", "guest", "held", "chunk", "word", "rep", "quality_score", "copies")})


@pytest.fixture(scope="module")
def none(spark):
    return docs_of(spark, [])


@pytest.fixture(scope="module")
def real(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def texts(real):
    return {r.doc_id: r.text or "" for r in real.collect()}


def low(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", low(t))


# 1


def exact_brute(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[low(t)].append(i)
    return Counter((i, hashlib.sha256(low(t).encode()).hexdigest(), max((x for x in groups[low(t)] if x is not None), default=None), len(groups[low(t)])) for i, t in rows)


def test_exact_duplicates(spark, odd, none, texts, real):
    for df, rows in ((odd, [r[:2] for r in ODD]), (real, list(texts.items()))):
        want = exact_brute(rows)
        # A sieve of two places lets nearly everything through: the answers are the same.
        for places in (exact.SIEVE, 2):
            was, exact.SIEVE = exact.SIEVE, places
            try:
                got = exact.exact_duplicates(df, every_digest=True).collect()
                some = exact.exact_duplicates(df).collect()
            finally:
                exact.SIEVE = was
            assert Counter((r.doc_id, r.digest, r.keep_id, r.group_size) for r in got) == want
            assert all(r.kept == (r.doc_id == r.keep_id) for r in got)
            assert Counter((r.doc_id, r.digest, r.keep_id, r.group_size) for r in some) == Counter({(i, d if n > 1 else None, k, n): c for (i, d, k, n), c in want.items()})
    assert exact.exact_duplicates(none).count() == 0
    kept = exact.keep_exact(odd)
    assert kept.columns == odd.columns and kept.count() == len({low(r[1]) for r in ODD})
    clashing = odd.withColumns({c: F.lit("mine") for c in ("_digest", "_keep_id", "row", "place", "sieve", "shared", "id", "m")})
    clash = exact.keep_exact(clashing)
    assert clash.columns == clashing.columns and clash.filter("sieve = 'mine' and _keep_id = 'mine'").count() == kept.count()
    named = docs_of(spark, ODD).withColumn("doc_id", F.concat(F.lit("d"), "doc_id"))
    assert exact.keep_exact(named).count() == kept.count() and exact.exact_duplicates(named).count() == len(ODD)


# 2


def test_fingerprints_are_sums():
    a, b = "one two three\nfour five six", "four five six\n\none two three  "
    fa, fb, part, rest = fingerprints.paragraph_vectors([a, b, "one two three", "four five six"])
    assert (fa == fb).all()
    assert fingerprints.add(part.tobytes(), rest.tobytes()) == fa.tobytes()
    assert fingerprints.add(fa.tobytes(), rest.tobytes(), -1) == part.tobytes()
    assert not fingerprints.paragraph_vectors([""]).any()
    assert (fingerprints.paragraph_vectors(["x", "x\nx"])[0] != fingerprints.paragraph_vectors(["x", "x\nx"])[1]).any()


def edited_brute(rows):
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1]), reverse=True)
    out = []
    for k, (i, t) in enumerate(order):
        u = order[(k + 1) % len(order)][1]
        out.append((i, len(t), hashlib.sha256((t[: len(t) - len(t) // 2] + u[: len(t) // 2]).encode()).hexdigest()))
    return sorted(out, key=str)


def test_edited_texts(odd, none, real, texts, spark):
    for df, rows in ((odd, [(i, t or "") for i, t, *_ in ODD]), (real, list(texts.items()))):
        got = fingerprints.edited(df).collect()
        assert sorted(((r.doc_id, r.n_chars, r.edited_sha256) for r in got), key=str) == edited_brute(rows)
        assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    long = [r for r in fingerprints.edited(real).collect() if r.n_chars > 500]
    assert np.mean([r.near_edited > r.near_next for r in long]) > 0.9
    assert fingerprints.edited(none).count() == 0
    one = fingerprints.edited(docs_of(spark, [(1, "a b", None, None, 1)])).collect()
    assert len(one) == 1 and one[0].near_next == 1
    prints = {r.doc_id: r.fingerprint for r in fingerprints.fingerprint(real).collect()}
    same = defaultdict(set)
    for i, t in texts.items():
        same[t].add(prints[i])
    assert all(len(s) == 1 for s in same.values())


# 3


def mixing_brute(rows, entropy, budget_share, seed):
    sized = [(i, s or "", len(words(t)), hashlib.md5(f"{seed}:{i if i is not None else ''}".encode()).hexdigest()) for i, t, s in rows]
    totals = Counter()
    for _, s, n, _ in sized:
        totals[s] += n
    total = sum(totals.values())
    share = {s: n / total for s, n in totals.items() if n}

    def h(a):
        p = [x**a for x in share.values()]
        return math.log(sum(p)) - sum(x * math.log(x) for x in p) / sum(p)

    low_, high = 0.0, 1.0
    for _ in range(80):
        mid = (low_ + high) / 2
        low_, high = (mid, high) if h(mid) >= entropy * math.log(len(share)) else (low_, mid)
    if h(1.0) >= entropy * math.log(len(share)):
        low_ = 1.0
    norm = sum(x**low_ for x in share.values())
    return low_, {s: x**low_ / norm for s, x in share.items()}


def test_mixing(odd, none, real, texts):
    rows = [(r.doc_id, r.text, r.source) for r in real.select("doc_id", "text", "source").collect()]
    for entropy in (0.5, 0.97, 0.995):
        got = mixing.mix_sources(real, entropy=entropy, seed=3).collect()
        a, weight = mixing_brute(rows, entropy, 1.0, 3)
        assert len(got) == len(rows)
        assert all(abs(r.weight - weight[r.source]) < 1e-5 for r in got)
        total = sum(r.tokens for r in got)
        by = defaultdict(list)
        for r in got:
            by[r.source].append(r)
        for s, rs in by.items():
            part, size = math.floor(rs[0].weight * total), rs[0].source_tokens
            rs.sort(key=lambda r: r.start)
            at = 0
            for r in rs:
                assert r.start == at and r.copies == part // size + (r.start < part % size)
                at += r.tokens
            taken = sum(r.copies * r.tokens for r in rs)
            assert part <= taken < part + max(r.tokens for r in rs)
    twice = mixing.mix_sources(real, repeats=2.0, budget_share=1.5).agg(F.max("copies")).first()[0]
    assert twice <= 3
    got = mixing.mix_sources(odd, entropy=0.9).collect()
    assert len(got) == len(ODD) and {r.source for r in got} == {"", "a", "b", "c"}
    assert mixing.mix_sources(none, entropy=0.9).count() == 0
    clashing = odd.withColumns({c: F.lit("mine") for c in ("_copies", "_mix_id", "_copy", "row", "id", "copies", "block", "span")})
    out = mixing.mixed(clashing, entropy=0.9)
    assert out.columns == clashing.columns and out.filter("copies = 'mine' and span = 'mine'").count() == mixing.mixed(odd, entropy=0.9).count() > 0
    # Short blocks and spans: the order is another one, its laws are the same.
    small = (mixing.BLOCK_TOKENS, mixing.SPAN_BLOCKS)
    mixing.BLOCK_TOKENS, mixing.SPAN_BLOCKS = 100, 3
    try:
        got = mixing.mix_sources(real, entropy=0.97, seed=3).collect()
    finally:
        mixing.BLOCK_TOKENS, mixing.SPAN_BLOCKS = small
    for s in {r.source for r in got}:
        rs = sorted((r for r in got if r.source == s), key=lambda r: (r.start, r.block_rank, r.tokens > 0))
        at = 0
        for r in rs:
            assert r.start == at
            at += r.tokens
        ranks = [r.block_rank for r in rs if r.tokens]
        assert ranks == sorted(ranks) and len({r.block for r in rs}) == len({r.block_rank for r in rs}) == max(r.block_rank for r in rs)
    with pytest.raises(ValueError):
        mixing.mix_sources(real)


# 4


def test_licences(spark, odd, none):
    mit = next(t for n, t in licences.NOTICES if t.startswith("MIT License"))
    rows = [
        (1, mit, None, None, 1), (2, mit.upper().replace(",", " ,;").replace("\n\n", "\nCopyright (c) 2020 Someone Else\nAll rights reserved.\n"), None, None, 1), (3, "Text.\nReleased under the MIT Licence!\nMore text.", None, None, 1),
        (4, "Released under the MIT License.\nLicensed under CC BY 4.0", None, None, 1), (5, "the MIT License is released", None, None, 1), (6, mit + "\nand more", None, None, 1),
    ]
    got = {r.doc_id: r for r in licences.scan(docs_of(spark, rows)).collect()}
    assert got[1].licence == got[2].licence == "MIT" and got[1].canonical_sha256 == got[2].canonical_sha256
    assert got[3].licence is None and got[3].notices == ["MIT"] and got[4].notices == ["CC-BY-4.0", "MIT"]
    assert got[5].licence is None and got[5].notices == [] and got[6].licence is None
    odd_rows = licences.scan(odd).collect()
    assert len(odd_rows) == len(ODD) and all(r.licence is None for r in odd_rows) and licences.scan(none).count() == 0
    # Licence texts as Debian has them, where this machine is one; whole words only are spelled anew.
    debian = Path("/usr/share/common-licenses")
    if (debian / "MPL-2.0").exists():
        whole = [(k, (debian / f).read_text(), None, None, 1) for k, f in enumerate(("Apache-2.0", "MPL-2.0", "GPL-3"))]
        whole += [(k + 10, "\n\n" + t.upper().replace(".", " ,") + "\n \n", *rest) for k, t, *rest in whole]
        names = {r.doc_id: r.licence for r in licences.scan(docs_of(spark, whole)).collect()}
        assert names == {0: "Apache-2.0", 1: "MPL-2.0", 2: "GPL-3.0", 10: "Apache-2.0", 11: "MPL-2.0", 12: "GPL-3.0"}
    forms = spark.createDataFrame([("super center  Licence licence\n\n sub-license",), ("\n. \n",)], "t string").select(licences.canonical_lines(F.col("t"))).collect()
    assert [r[0] for r in forms] == ["super center license license\nsublicense", ""]
    # A known text without words matches no empty text, and many known texts give the same answers.
    many = [(n, t) for n, t in licences.NOTICES] + [("empty", " . ")] + [(f"L{k}", f"text number {k} of many") for k in range(3000)]
    again = {r.doc_id: (r.licence, r.notices) for r in licences.scan(docs_of(spark, [*rows, (7, "", None, None, 0), (8, "a\nText number 17 of many", None, None, 0)]), licences.known_licences(spark, many)).collect()}
    assert again == {i: (r.licence, r.notices) for i, r in got.items()} | {7: (None, []), 8: (None, ["L17"])}
    assert licences.scan(docs_of(spark, rows), licences.known_licences(spark, [("mine", "other")])).filter("licence is not null").count() == 0


# 5


def test_archives(spark, tmp_path, sf):
    big = "<p>" + "é" * 600
    rows = [(1, "u1", big), (5, "u5", big), (3, "u3\r\n", big), (2, "u2", "small"), (4, "u4", "small"), (6, None, None), (7, "u7", ""), (5, "u5", big), (None, "u", big), (8, "u8", "a\r\n\r\nWARC/1.1\r\n\r\n")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("header", F.lit("clash"))
    records = warc.records_of(pages)
    warc.write_archive(records, str(tmp_path / "a"))
    back = warc.read_archive(spark, str(tmp_path / "a"))
    got = sorted(((r.page_id, bytes(r.payload), r.record_type, r.refers_to) for r in back.collect()), key=str)
    want = sorted(((i, (h or "").encode(), *(("revisit", 5) if h == big and i != 5 else ("response", None))) for i, _, h in rows), key=str)
    assert got == want
    assert spark.read.parquet(str(tmp_path / "a/payloads")).count() == 4
    assert warc.read_archive(spark, str(tmp_path / "a")).select(warc.header_field("WARC-Type").alias("t")).filter("t = 'revisit'").count() == 3
    warc.write_warc_files(records, str(tmp_path / "w"))
    files = warc.read_warc_files(spark, str(tmp_path / "w")).collect()
    assert sorted((r.type, bytes(r.payload)) for r in files) == sorted((t, h if t == "response" else b"") for _, h, t, _ in want)
    made = {bytes(r.record) for r in warc.record_bytes(back).collect()}
    assert {r.header.encode() + bytes(r.payload) + b"\r\n\r\n" for r in files} == made
    warc.archive(pages, str(tmp_path / "p"))
    assert sorted(((r.page_id, bytes(r.payload), r.record_type, r.refers_to) for r in warc.read_archive(spark, str(tmp_path / "p")).collect()), key=str) == want
    assert spark.read.parquet(str(tmp_path / "p/payloads")).count() == 4
    empty = spark.createDataFrame([], "page_id bigint, url string, html string")
    warc.write_archive(warc.records_of(empty), str(tmp_path / "e"))
    assert warc.read_archive(spark, str(tmp_path / "e")).count() == 0
    spark.read.parquet(str(tmp_path / "a/payloads")).withColumn("payload", F.lit(b"bad")).write.parquet(str(tmp_path / "b/payloads"))
    spark.read.parquet(str(tmp_path / "a/headers")).write.parquet(str(tmp_path / "b/headers"))
    with pytest.raises(Exception, match="payload does not have the digest"):
        warc.read_archive(spark, str(tmp_path / "b")).collect()


# 6


def test_bpe_is_the_librarys(odd, none, real, texts):
    tokenizers = pytest.importorskip("tokenizers")
    path = queries.tokenizer_path()
    t = tokenizers.Tokenizer.from_file(path)
    t.no_truncation()
    t.no_padding()
    for df, rows in ((odd, [(i, x or "") for i, x, *_ in ODD]), (real, list(texts.items()))):
        got = bpe.decode(bpe.encode(df, path), path).collect()
        want = []
        for i, x in rows:
            ids = t.encode(x, add_special_tokens=False).ids
            want.append((i, len(ids), ids, t.decode(ids, skip_special_tokens=False)))
        assert sorted(((r.doc_id, r.n_tokens, np.frombuffer(r.token_ids, "<u4").tolist(), r.decoded) for r in got), key=str) == sorted(want, key=str)
    assert bpe.encode(none, path).count() == 0
    tables = bpe.load_tables(path)
    samples = ["aaaaaaaaa", "", "I'LL we've 'S", "ΣΑΣ İ ẞ", "<|startoftext|><|endoftext|>x<|endoftext", "\u0085a b\x1cc", "ﬁ é é", "１２3", "🎉🎉🎉"]
    coder = bpe.Encoder(tables)
    assert [np.frombuffer(b, "<u4").tolist() for b in coder.encode(samples)] == [t.encode(x, add_special_tokens=False).ids for x in samples]
    was, bpe.MOST_KEPT = bpe.MOST_KEPT, 3
    try:
        assert coder.encode(samples) == bpe.Encoder(tables).encode(samples)
    finally:
        bpe.MOST_KEPT = was


# 7


def katz_brute(rows):
    """The model by dictionaries; gives n_known, base and score per row, and the function p(w, u)."""
    tok = [[*words(t), None] for _, t in rows]
    held = [zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2 for i, _ in rows]
    uni, bi = Counter(), Counter()
    for h, ws in zip(held, tok, strict=True):
        if not h:
            uni.update(ws)
            bi.update(zip([None, *ws[:-1]], ws, strict=True))
    n, v = sum(uni.values()), len(uni)
    freq = lambda c: [0, *(sum(1 for x in c.values() if x == r) for r in range(1, 7))]
    d1, d2 = katz.discounts(freq(uni)), katz.discounts(freq(bi))
    left = sum(c * (1 - d1[c]) for c in uni.values() if c <= 5)
    scale = n if left > 0 else n + 1
    p1 = lambda w: uni[w] * (d1[uni[w]] if uni[w] <= 5 else 1) / scale if uni[w] else (left if left > 0 else 1) / scale
    after = defaultdict(dict)
    for (u, w), c in bi.items():
        after[u][w] = c

    def p(w, u):
        seen = after.get(u)
        if not seen:
            return p1(w)
        low_counts = [c for c in seen.values() if c <= 5]
        whole = uni[u] + (not low_counts)
        if w in seen:
            return seen[w] * (d2[seen[w]] if seen[w] <= 5 else 1) / whole
        rest = sum(c * (1 - d2[c]) for c in low_counts) if low_counts else 1
        return rest / whole / (1 - sum(p1(x) for x in seen)) * p1(w)

    out = []
    for (i, _), h, ws in zip(rows, held, tok, strict=True):
        base = sum(math.log10((uni[w] + 1) / (n + v + 1)) for w in ws)
        out.append((i, h, len(ws), sum(uni[w] > 0 for w in ws), n, base, sum(math.log10(p(w, u)) for u, w in zip([None, *ws[:-1]], ws, strict=True))))
    return out, p, uni


def close(a, b):
    return a[:5] == b[:5] and all(abs(x - y) < 1e-6 * max(1, abs(y)) for x, y in zip(a[5:], b[5:], strict=True))


def test_katz(odd, none, real, texts):
    for df, rows in ((real, list(texts.items())), (odd, [(i, t or "") for i, t, *_ in ODD])):
        want, p, uni = katz_brute(rows)
        got = sorted(map(tuple, katz.score(df).collect()), key=str)
        assert len(got) == len(want) and all(close(g, w) for g, w in zip(got, sorted(want, key=str), strict=True))
        for u in [None, *list(uni)[:40], "never seen"]:
            assert abs(sum(p(w, u) for w in uni) + p("never seen either", u) - 1) < 1e-9
    held = [r for r in katz.score(real).collect() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
    assert katz.score(none).count() == 0
    untrained = katz.score(real, held=F.lit(True)).agg(F.sum("score"), F.sum("n_known"), F.max("train_tokens")).first()
    assert tuple(untrained) == (0.0, 0, 0)


def test_katz_with_hot_contexts(spark):
    """One word between all others: its pairs are spread over the partitions by both words."""
    rows = [(i, " ".join(f"the w{(i * 7 + k) % 53}" for k in range(30))) for i in range(60)]
    df = spark.createDataFrame([(i, t, None, None, 1) for i, t in rows], SCHEMA)
    got = sorted(map(tuple, katz.score(df).collect()), key=str)
    assert all(close(g, w) for g, w in zip(got, sorted(katz_brute(rows)[0], key=str), strict=True))


# 8


def distance(x, y):
    d = list(range(len(y) + 1))
    for i, a in enumerate(x, 1):
        p, d[0] = d[0], i
        for j, b in enumerate(y, 1):
            p, d[j] = d[j], min(p + (a != b), d[j] + 1, d[j - 1] + 1)
    return d[-1]


def test_distances():
    import random

    r = random.Random(5)
    pairs, most, want = [], [], []
    for _ in range(200):
        x = [r.randrange(6) for _ in range(r.randrange(50))]
        y = [v for v in x if r.random() > 0.15]
        for _ in range(r.randrange(12)):
            y.insert(r.randrange(len(y) + 1), r.randrange(6))
        m = r.randrange(20)
        d = distance(x, y)
        pairs.append((np.array(x, np.uint32), np.array(y, np.uint32)))
        most.append(m)
        want.append(d if d <= m else -1)
    assert near.edit_distances(pairs, most) == want
    was = near.WHOLE, near.BAND, near.WIDE
    try:
        for near.WHOLE, near.BAND, near.WIDE in ((0, 1, 1 << 15), (0, 2, 1)):
            assert near.edit_distances(pairs, most) == want
    finally:
        near.WHOLE, near.BAND, near.WIDE = was
    # Long texts: 30,000 words with a tenth of them changed, and with more changes than the limit lets pass.
    long = np.arange(30_000, dtype=np.uint32) % 997
    other = long.copy()
    other[::10] = 5000
    assert near.edit_distances([(long, other)] * 2, [6000, 2999]) == [3000, -1]


def test_bounds_of_word_counts():
    """No pair that is similar enough is ruled out, whatever its lengths and blocks, and unlike texts are."""
    rng = np.random.default_rng(9)
    texts = []
    for _ in range(60):
        base = rng.integers(0, 1 << 32, rng.integers(1, 400), dtype=np.uint64).astype(np.uint32)
        for share in (0, 0.1, 0.25):
            copy = base[rng.random(len(base)) >= share / 2]
            copy[rng.random(len(copy)) < share / 2] = 7
            texts.append(copy if len(copy) else base)
    n, bins = np.array([len(t) for t in texts]), [np.frombuffer(near.word_bins(t), np.uint8) for t in texts]
    part = np.arange(len(texts))
    part[5] = part[4]
    for own in (np.zeros(len(texts), int), np.arange(len(texts)) % 2):
        got = {(min(a, b), max(a, b)) for a, b, _ in zip(*near.count_pairs(n, part, own, bins, 0.8), strict=True)}
        all_pairs = [(a, b) for b in range(len(texts)) for a in range(b) if part[a] != part[b] and (own[a] != own[b] or not own.any())]
        close = near.edit_distances([(texts[a], texts[b]) for a, b in all_pairs], [near.similarity_at_least(texts[a], texts[b], 0.8) for a, b in all_pairs])
        links = {p for p, d in zip(all_pairs, close, strict=True) if d >= 0}
        assert links <= got <= set(all_pairs) and len(got) < len(links) + 0.1 * len(all_pairs)
        every = Counter(a for a, _, _ in zip(*near.count_pairs(n, part, own, bins, 0.8), strict=True))
        few = list(zip(*near.count_pairs(n, part, own, bins, 0.8, 1), strict=True))
        assert {(min(a, b), max(a, b)) for a, b, _ in few} <= got and {a: more for a, _, more in few} == {a: c > 1 for a, c in every.items()}

    # Members of several buckets: every pair that any of them gives comes once, from the bucket with its lowest key.
    own, keys = np.zeros(len(texts), int), [np.sort(rng.choice(30, rng.integers(1, 9), replace=False)) for _ in texts]
    for lower in (False, True):
        given = Counter()
        for key in range(30):
            at = [i for i, k in enumerate(keys) if key in k]
            below = [keys[i][keys[i] < key] for i in at] if lower else None
            found = near.count_pairs(n[at], part[at], own[at], [bins[i] for i in at], 0.8, None, below) if at else ((), (), ())
            given.update((min(at[a], at[b]), max(at[a], at[b])) for a, b, _ in zip(*found, strict=True))
        if lower:
            assert set(given) == several and set(given.values()) == {1}
        several = set(given)


def test_bucket_of_unlike_texts(spark):
    """Texts with one passage in common and nothing else: the two that are alike find each other, whatever the blocks."""
    rng = np.random.default_rng(2)
    passage = " ".join(f"common{i}" for i in range(60))
    rows = [(k, passage + " " + " ".join(f"own{x}" for x in rng.integers(0, 10**9, 60)), None, None, 1) for k in range(150)]
    twin = rows[3][1].split()
    twin[70:80] = ["changed"] * 10
    rows.append((200, " ".join(twin), None, None, 1))
    for near.BLOCK in (16, 4096):
        got = {r.doc_id: r.class_id for r in near.near_duplicates(docs_of(spark, rows)).collect()}
        assert got == {k: k for k in range(150)} | {3: 200, 200: 200}
    with pytest.raises(TypeError):
        near.near_duplicates(docs_of(spark, rows).withColumn("doc_id", F.lit("a")))


def test_sketches_follow_order():
    a = " ".join(f"w{i}" for i in range(60))
    b = " ".join(f"w{i}" for i in reversed(range(60)))
    c = a.replace("w30", "other")
    _, sizes, s = near.sketch_texts(pa.array([a, a.upper(), b, c, "", None, "w1 w2"]))
    assert (s[0] == s[1]).all() and (s[0] == s[2]).sum() == 0 and (s[0] == s[3]).sum() >= 4 and (s[4] == s[5]).all()
    assert sizes.tolist() == [60, 60, 60, 60, 0, 0, 2]


def near_brute(rows, least=0.8):
    toks = [words(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = set()
    for i in range(len(rows)):
        for j in range(i):
            n = max(len(toks[i]), len(toks[j]))
            if toks[i] == toks[j] or min(len(toks[i]), len(toks[j])) >= least * n and sum((Counter(toks[i]) & Counter(toks[j])).values()) >= least * n and distance(toks[i], toks[j]) <= (1 - least) * n + 1e-9:
                links.add((i, j))
                root[find(i)] = find(j)
    return links, [find(i) for i in range(len(rows))]


def test_near_duplicates(odd, none, real, texts):
    rows = [(i, t) for i, t in texts.items() if len(t) < 6000]
    links, _ = near_brute(rows)
    got = {r.doc_id: r.class_id for r in near.near_duplicates(real).collect()}
    assert len(got) == len(texts)
    found = sum(got[rows[i][0]] == got[rows[j][0]] for i, j in links)
    assert found >= 0.95 * len(links) > 0
    full = list(texts.items())
    groups = defaultdict(set)
    for i, t in full:
        groups[got[i]].add(i)
    for c, members in groups.items():
        assert c == max(members)
        if len(members) > 1:
            _, roots = near_brute([(i, texts[i]) for i in sorted(members)])
            assert len(set(roots)) == 1, "a class is held together by true links"
    odd_rows = near.near_duplicates(odd).collect()
    by = defaultdict(set)
    for r in odd_rows:
        by[r.doc_id].add(r.class_id)
    assert len(odd_rows) == len(ODD) and by[1] == by[2] == by[3] == {3} and by[4] == {5} and by[6] == {7} and by[9] == by[12] and by[None] == {None}
    assert near.near_duplicates(none).count() == 0
    clashing = odd.withColumns({c: F.lit("mine") for c in ("_gone", "row", "id")})
    assert near.keep_near(clashing).columns == clashing.columns and near.keep_near(clashing).count() == sum(r.kept or r.doc_id is None for r in odd_rows)


def test_large_group_of_near_copies(spark):
    """Hundreds of edits of one text: one class, and few pairs."""
    base = [f"v{i}" for i in range(120)]
    rows = []
    for k in range(300):
        w = list(base)
        for j in range(5):
            w[(k * 37 + j * 23) % 120] = f"edit{k}_{j}"
        rows.append((k, " ".join(w), None, None, 1))
    got = near.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()
    assert {r.class_id for r in got} == {299} and sum(r.kept for r in got) == 1


def test_sketches_stand_alone():
    texts = ["a b c d e f g", "x y z x y z x y z", "", "a", "b a b a b a b a", "p q r s t u v w"]
    whole = near.sketch_texts(pa.array(texts))
    for k, t in enumerate(texts):
        alone = near.sketch_texts(pa.array([t]))
        assert all((x[k] == y[0]).all() for x, y in zip(whole, alone, strict=True))


def test_keys_reach_similar_texts(spark):
    """Nearly all pairs of similarity 0.8 share a sketch, and all pairs of short texts a key."""
    rng = np.random.default_rng(3)
    base = [[f"w{k}_{i}" for i in range(400)] for k in range(200)]
    edited = [[f"o{i}" if i in gone else w for i, w in enumerate(b)] for b in base for gone in [set(rng.choice(400, 80, replace=False).tolist())]]
    a, b = (near.sketch_texts(pa.array([" ".join(w) for w in x]))[2] for x in (base, edited))
    assert (a == b).any(axis=1).mean() >= 0.95
    for _ in range(3000):
        x = rng.integers(0, 12, rng.integers(1, near.SHORT + 1)).tolist()
        y = list(x)
        for _ in range(rng.integers(1, 4)):
            at, how = int(rng.integers(0, len(y) + 1)), rng.integers(3)
            y[at : at + (how != 0)] = [] if how == 1 else [int(rng.integers(0, 40))]
        longest = max(len(x), len(y))
        if y and longest <= near.SHORT and x != y and distance(x, y) <= 0.2 * longest + 1e-9:
            assert set(near.short_keys(np.array(x, np.uint64))) & set(near.short_keys(np.array(y, np.uint64)))
    rows = [(1, "a b c d e f g h i", None, None, 1), (2, "a b c d x f g h i", None, None, 1), (3, "k l m n o", None, None, 1), (4, "k l y n o", None, None, 1)]
    assert {r.doc_id: r.class_id for r in near.near_duplicates(docs_of(spark, rows)).collect()} == {1: 2, 2: 2, 3: 4, 4: 4}


def test_star_of_near_copies(spark):
    """Copies that are like a common text only, whose id is the smallest: one class, as all its links run over that text."""
    rng = np.random.default_rng(5)
    base = [f"b{i}" for i in range(400)]
    rows = [(0, " ".join(base), None, None, 1)]
    for k in range(1, 121):
        w = list(base)
        for i in rng.choice(400, 48, replace=False):
            w[i] = f"other{k}_{i}"
        rows.append((k, " ".join(w), None, None, 1))
    sketches = near.sketch_texts(pa.array([r[1] for r in rows]))[2]
    reached = {k for k in range(1, 121) if (sketches[k] == sketches[0]).any()}
    got = {r.doc_id: r.class_id for r in near.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert len(reached) > 90 and all(got[k] == got[0] == max(reached) for k in reached)


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, k) for k in range(101, 140)] + [(7, 7), (200, 201), (200, 201)]
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
    assert all(got[i] == 40 for i in range(41)) and all(got[i] == 139 for i in range(100, 140)) and got[200] == got[201] == 201


# 9


PAGE = """<!DOCTYPE html><html><head><title>The title</title><style>p{}</style><script>var t="</p>";</script></head><body class="with-sidebar">
<header><a href="/">Home</a><div>Site of the year</div></header><nav><ul><li><a href="/a">The menu of it</a></li></ul></nav>
<div class="cookie-notice">This site uses cookies and it is for you to accept them in the settings of the browser.</div>
<article class="post"><h1>Head &amp; line</h1><p>First of the <b>bold</b> para&shy;graph&nbsp;with<br>a break.</p><!-- <p>gone</p> --><p>Short.
<div class="adBox">Buy the thing that is on sale in the shop of the town today.</div><p title="a > b">Third &lt;b&gt; one</p><form><label>Mail</label><input value="x"></form>
<aside>Related to this is that</aside><p><a href="/x">linked</a> words in the text that is of use</p></article>
<section id="comments"><p>I think that this is the best of all the articles that were on the site.</p></section><footer>&copy; The footer of the page</footer></body></html>"""


def test_main_text(spark):
    assert html.main_text(PAGE).split("\n") == ["Head & line", "First of the bold para­graph with a break.", "Short.", "Third <b> one", "linked words in the text that is of use"]
    prose = "The cat sat on the mat and it was there for all of the day with a hat that is in the house. " * 4
    plain = f"<div><a href=1>a</a> <a href=2>b</a></div><div>{prose}</div><p>Tiny bit</p><div>{prose}</div><div><a href=3>Next</a></div>"
    assert html.main_text(plain).split("\n") == [prose.strip(), "Tiny bit", prose.strip()]
    wrapped = f'<div class="page has-sidebar with-ads"><main id="content"><p>{prose}</p></main><article class="comment"><p>{prose}</p></article><div id="mainMenu">{prose}</div></div>'
    assert html.main_text(wrapped) == prose.strip()
    for odd_page in (None, "", "<", "<p", "<p class='x", "text only", "<script>never closed", "</p></div>", "<a href=\"x>y", "<![CDATA[x]]>", "<p>" * 3000 + "x", "<!-- open"):
        html.main_text(odd_page)
    df = spark.createDataFrame([(1, "u", PAGE), (1, "u", PAGE), (2, None, None), (None, "v", "")], "page_id bigint, url string, html string").withColumn("text", F.lit("clash"))
    got = sorted(((r.page_id, r.url, r.text) for r in html.extract(df).collect()), key=str)
    assert len(got) == 4 and (2, None, "") in got and got[0] == got[1]
    assert html.extract(df.limit(0)).count() == 0


def test_articles_of_the_pages(spark, sf):
    import html as entities

    rows = spark.read.parquet(f"{sf}/pages.parquet").collect()
    for r in rows:
        m = re.search(r"<article>(.*?)</article>", r.html or "", re.S)
        blocks = re.split(r"</?(?:p|h1)>", m[1]) if m else []
        want = [" ".join(entities.unescape(re.sub(r"<[^>]*>", "", b.replace("<br>", " "))).split()) for b in blocks]
        assert html.main_text(r.html) == "\n".join(b for b in want if b)


def brute_text(page):
    """Both passes over the blocks, each neighbour looked for anew."""
    blocks = html.blocks_of(page)
    has = any(b.story and not b.away for b in blocks)
    labels = []
    for b in blocks:
        toks = re.findall(r"\w+", b.text.lower())
        stops = sum(t in html.STOP_WORDS for t in toks) / max(len(toks), 1)
        links = min(1, b.linked / len(b.text))
        if b.away or has and not b.story:
            step = (1 if b.story else -1 if has else 0) - (3 if b.away else 0)
            rich = links <= 0.2 and len(b.text) >= 70 and stops >= html.MANY_STOPS and len(b.text) > 200
            labels.append("good" if rich and step >= 0 else "near" if rich and step == -1 else "bad")
        elif b.story:
            if links > 0.5 and stops < html.FEW_STOPS:
                labels.append("brief" if len(toks) <= 3 else "bad")
            elif len(b.text) < 70 and stops < html.FEW_STOPS:
                labels.append("brief")
            else:
                labels.append("good" if stops >= html.FEW_STOPS else "near")
        elif links > 0.2 or len(b.text) < 70 and b.linked:
            labels.append("bad")
        elif len(b.text) < 70:
            labels.append("brief")
        else:
            labels.append("bad" if stops < html.FEW_STOPS else "good" if stops >= html.MANY_STOPS and len(b.text) > 200 else "near")
    out = []
    for i, b in enumerate(blocks):
        sides = []
        for order in (range(i - 1, -1, -1), range(i + 1, len(blocks))):
            decided = [blocks[j] for j in order if labels[j] in ("good", "bad") and not (blocks[j].story and blocks[j].away)]
            own = [x for x in decided if b.story and x.story == b.story] or [x for x in decided if not b.story and x.holder == b.holder]
            pick = own[0] if own else decided[0] if decided and not b.story and not has else None
            sides.append((labels[blocks.index(pick)] == "good", pick.holder == b.holder) if pick else (bool(b.story), bool(b.story)))
        good = [x for x in sides if x[0]]
        if labels[i] == "good" or labels[i] == "near" and good or labels[i] == "brief" and (len(good) == 2 or len(good) == 1 and (b.story or good[0][1])):
            out.append(b.text)
    return "\n".join(out)


def test_two_passes(sf):
    """Against a plain version on random pages, whose blocks are all different."""
    rng = np.random.default_rng(11)
    stops = sorted(html.STOP_WORDS)
    for _ in range(400):
        parts = []
        for k in range(int(rng.integers(1, 14))):
            toks = [stops[int(rng.integers(len(stops)))] if rng.random() < 0.2 else f"word{k}" for _ in range(int(rng.choice([1, 3, 12, 60])))] + [f"end{k}"]
            text = " ".join(toks)
            text = f"<a href=x>{text}</a>" if rng.random() < 0.2 else text
            parts.append(str(rng.choice(["<p>{}</p>", "<div>{}</div>", "<nav>{}</nav>", "<article>{}", "</article>{}", "<div class=ad>{}</div>", "<h2>{}</h2>", "<section><p>{}</p></section>", "<p class=comment>{}</p>"])).format(text))
        page = "".join(parts)
        assert html.main_text(page) == brute_text(page), page


def test_pages_without_article_tags(spark):
    """The text rules alone: most of an article is found when nothing says where it is."""
    found = wanted = kept = 0
    for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect():
        want = Counter(html.main_text(r.html).split("\n"))
        got = Counter(html.main_text(re.sub(r"</?article[^>]*>", "", r.html or "")).split("\n"))
        size = lambda c: sum(len(k) * v for k, v in c.items())
        found, wanted, kept = found + size(want & got), wanted + size(want), kept + size(got)
    assert found >= 0.85 * wanted and found >= 0.98 * kept


def test_broken_pages_take_linear_time():
    for page in ("<a" * 10**6, "<div>" * 10**5, '<a ">" ' * 10**5, '<a =">" ' * 10**5, '<a x="' * 10**5, "<a " + "b " * 10**5, "<" * 10**5, "<!-" * 10**5, "<script>" * 10**5, "<p hidden" + " " * 10**5 + ">", "<p a=" + " " * 10**5 + ">"):
        began = time.monotonic()
        html.main_text(page)
        assert time.monotonic() - began < 3, page[:20]
    prose = "the one that is after it and to the end of it in all of the days that are to be " * 3
    assert html.main_text(f'<p a="x>first</p><div>{prose}</div>') == prose.strip()


# 10


def test_quality(spark, sf, odd, none):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = queries.quality_model(docs, labels)
    got = quality.score(docs.select("doc_id", "text"), model).join(labels, "doc_id").filter(F.crc32(F.col("doc_id").cast("string")) % 5 == 0).collect()
    good, bad = [r.quality_score for r in got if r.quality], [r.quality_score for r in got if not r.quality]
    assert np.mean([g > b for g in good for b in bad]) > 0.9
    assert np.mean([s >= quality.THRESHOLD for s in good]) > 0.95 and np.mean([s < quality.THRESHOLD for s in bad]) > 0.5
    rows = quality.score(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.quality_score <= 1 for r in rows)
    assert len({r.quality_score for r in rows if r.doc_id in (6, 7)}) == 1
    assert quality.score(none, model).count() == 0
    empty = quality.train(none, labels.limit(0))
    assert abs(quality.scores(pa.array(["x", None]), empty["w"], empty["bias"])[0] - 0.5) < 1e-9


def test_scores_are_dot_products():
    w = np.random.default_rng(1).normal(size=1 << quality.BITS).astype(np.float32)
    texts = ["the cat sat", "", "A!! B!! C!!", None, "x"]
    index, first = quality.features(pa.array(texts))
    for k, s in enumerate(quality.scores(pa.array(texts), w, 0.3)):
        mine = index[first[k] : first[k + 1]]
        z = 0.3 + quality.SCALE * (w[mine].astype(float).mean() if len(mine) else 0)
        assert abs(s - 1 / (1 + math.exp(-z))) < 1e-9
    alone = [quality.features(pa.array([t]))[0].tolist() for t in texts]
    assert [index[a:b].tolist() for a, b in zip(first[:-1], first[1:], strict=True)] == alone


def test_word_hashes_stand_alone():
    texts = ["The  cat\tSAT", "", None, "the", "cat\n", "sat the"]
    h, first = hashed_words(pa.array(texts))
    assert first.tolist() == [0, 3, 3, 3, 4, 5, 7]
    assert h[0] == h[3] == h[6] and h[1] == h[4] and h[2] == h[5] and len(set(h.tolist())) == 3

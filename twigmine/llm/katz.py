"""Language-model scoring by Katz backoff over words: Good-Turing discounted counts, exactly normalised backoff weights.

P(w | u) is d * c(u, w) / c(u) where the pair was seen in training and bow(u) * P(w) where not; P(w) is d * c(w) / N, and what the
discounts leave is the probability of the one class of unknown words.  Counts live in tables partitioned by a hash: words by
themselves, pairs by their first word (those of very frequent first words by both).  Documents are dealt to chunks by a hash; a chunk asks the partitions for the counts of the
different words and pairs it holds, each once, and scores its documents token by token, from pair to word to unknown,
with the answers.  So what is moved follows the number of different words and pairs of the chunks, and neither a table nor
a group of documents is ever in one place.

The model is a proper distribution over the training words, the end and the unknown class.  A begin is the end before it.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hashed_words, mix, release, store, trim, width

#: UTF-8 bytes of text in a chunk, and of all text for one table partition.
CHUNK_BYTES, PART_BYTES = 5_000_000, 10_000_000
#: Counts up to this are discounted.
MOST_DISCOUNTED = 5
END = np.uint64(0xE4D0F7E87A11AD05)
_G = np.uint64


def discounts(freq: list[int]) -> np.ndarray:
    """Factor for counts 0..MOST_DISCOUNTED, from freq[r] (r up to MOST_DISCOUNTED + 1): how many have the count r.

    Katz's form of Good-Turing; if a needed frequency is 0 or a factor leaves (0, 1), half a count is taken off instead.
    """
    k = MOST_DISCOUNTED
    d = np.ones(k + 1)
    if all(freq[r] > 0 for r in range(1, k + 2)):
        common = (k + 1) * freq[k + 1] / freq[1]
        if common < 1:
            for r in range(1, k + 1):
                d[r] = ((r + 1) * freq[r + 1] / freq[r] / r - common) / (1 - common)
            if ((d[1:] > 0) & (d[1:] < 1)).all():
                return d
    for r in range(1, k + 1):
        d[r] = (r - 0.5) / r
    return d


def planes(a: np.ndarray) -> bytes:
    """Numbers with their high bytes together, which pack to nothing where they are small."""
    a = np.ascontiguousarray(a)
    return np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T).tobytes()


def short(h: np.ndarray) -> bytes:
    """Six bytes of each hash, which tell the words behind one context apart: among f of them f*f / 2**49 pairs are taken for one."""
    return np.ascontiguousarray(h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].T).tobytes()


def unshort(b: bytes) -> np.ndarray:
    out = np.zeros((len(b) // 6, 8), np.uint8)
    out[:, :6] = np.frombuffer(b, np.uint8).reshape(6, -1).T
    return out.view("<u8").ravel()


def unplaned(b: bytes, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(kind).ravel()


def held_out(id_col: Column) -> Column:
    """Whether a document is kept out of training: crc32 of its id as text, modulo 7, is 2."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit(""))) % 7 == 2


class Chunk:
    """The tokens of a chunk's documents: words by number among the chunk's different words."""

    def __init__(self, docs: pa.Table, parts: int):
        words, first = hashed_words(pa.array([zlib.decompress(b) for b in docs.column("packed").to_pylist()], pa.binary()).cast(pa.string()))
        sizes = np.diff(first)
        n = self.n = len(sizes)
        self.held = docs.column("held").to_numpy(zero_copy_only=False).astype(bool)
        tokens = np.full(len(words) + n, END, np.uint64)
        tokens[np.arange(len(words)) + np.repeat(np.arange(n), sizes)] = words
        self.sizes = sizes + 1
        self.begin = np.cumsum(self.sizes) - self.sizes
        self.words, self.token = np.unique(tokens, return_inverse=True)
        self.end = int(np.searchsorted(self.words, END))
        self.trained = np.repeat(~self.held, self.sizes)
        self.part = (mix(self.words) % _G(parts)).astype(np.int64)
        self.order = np.argsort(self.part, kind="stable")
        self.parts = parts

    def word_requests(self):
        counts = np.bincount(self.token[self.trained], minlength=len(self.words)).astype(np.uint32)
        cut = np.searchsorted(self.part[self.order], np.arange(self.parts + 1))
        for b in np.flatnonzero(np.diff(cut)):
            at = self.order[cut[b] : cut[b + 1]]
            yield int(b), self.words[at].tobytes(), planes(counts[at])

    def take_counts(self, answers: dict[int, bytes]) -> None:
        self.count = np.zeros(len(self.words), np.int64)
        cut = np.searchsorted(self.part[self.order], np.arange(self.parts + 1))
        for b in np.flatnonzero(np.diff(cut)):
            self.count[self.order[cut[b] : cut[b + 1]]] = unplaned(answers[int(b)], "<i8")
        # A word that no other chunk holds came back with its count less one, negated.
        self.own = self.count < 0
        self.count = np.where(self.own, -1 - self.count, self.count)

    def pairs(self, hot_from: float) -> None:
        """Different pairs whose both words were seen in training, in the order of their table partitions."""
        before = np.empty_like(self.token)
        before[1:] = self.token[:-1]
        before[self.begin] = self.end
        self.before = before
        w = len(self.words)
        code, self.pair = np.unique(before.astype(np.int64) * w + self.token, return_inverse=True)
        u, v = code // w, code % w
        known = (self.count[u] > 0) & (self.count[v] > 0)
        counts = np.bincount(self.pair[self.trained], minlength=len(code))
        # Of a first word that no other chunk holds everything is known here.
        self.local = np.flatnonzero(known & self.own[u])
        self.local_u, self.local_v, self.local_count = u[self.local], v[self.local], counts[self.local]
        known &= ~self.own[u]
        self.asked = np.flatnonzero(known)
        u, v = u[known], v[known]
        hot = self.count[u] > hot_from
        part = np.where(hot, mix(self.words[u] ^ mix(self.words[v])) % _G(self.parts), self.part[u].astype(np.uint64)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        self.asked, self.u, self.v, self.hot, part = self.asked[order], u[order], v[order], hot[order], part[order]
        self.cut = np.searchsorted(part, np.arange(self.parts + 1))
        self.train_pairs = counts[self.asked]
        self.pair_held = np.zeros(w, bool)
        self.pair_held[before[~self.trained]] = True
        # First words of held-out tokens that were seen in training, but here before unknown words only: asked for without a pair.
        bare = self.pair_held & (self.count > 0) & ~self.own & (self.count <= hot_from)
        bare[self.u] = False
        bare = np.flatnonzero(bare)
        self.bare = bare[np.argsort(self.part[bare], kind="stable")]
        self.bare_cut = np.searchsorted(self.part[self.bare], np.arange(self.parts + 1))
        self.asked_parts = np.flatnonzero(np.diff(self.cut) + np.diff(self.bare_cut))

    def local_frequencies(self) -> bytes:
        """How many of the pairs that are not asked for have each low count."""
        c = self.local_count
        return np.bincount(c[(c > 0) & (c <= MOST_DISCOUNTED + 1)], minlength=MOST_DISCOUNTED + 2)[1:].astype(np.int64).tobytes()

    def contexts(self, b: int):
        """Of one partition: its pairs from and to, the first words asked for there, their numbers of pairs, and whether they are hot."""
        a, z = self.cut[b], self.cut[b + 1]
        u = self.u[a:z]
        start = np.flatnonzero(np.append(True, u[1:] != u[:-1])[: len(u)])
        bare = self.bare[self.bare_cut[b] : self.bare_cut[b + 1]]
        runs = np.append(np.diff(np.append(start, z - a)), np.zeros(len(bare), np.int64))
        return a, z, np.append(u[start], bare), runs, np.append(self.hot[a:z][start], np.zeros(len(bare), bool))

    def pair_requests(self):
        if not len(self.asked_parts):
            yield 0, b"", b"", b"", b"", b"", b""
        for b in self.asked_parts:
            a, z, u, runs, hot = self.contexts(b)
            flags = self.pair_held[u].astype(np.uint8) | (hot.astype(np.uint8) << 1)
            v = self.v[a:z]
            yield int(b), self.words[u].tobytes(), planes(runs.astype(np.uint32)), flags.tobytes(), short(self.words[v]), planes(self.count[v]), planes(self.train_pairs[a:z].astype(np.uint32))


class Words:
    """The unigram model: what the counts of words give."""

    def __init__(self, total: int, different: int, freq: list[int]):
        self.total, self.different = total, different
        self.d = discounts(freq)
        left = sum(freq[r] * r * (1 - self.d[r]) for r in range(1, MOST_DISCOUNTED + 1))
        # Without a discounted count one further token stands for the unknown class.
        self.scale = total if left > 0 else total + 1
        self.unknown = (left if left > 0 else 1) / self.scale

    def p(self, count: np.ndarray) -> np.ndarray:
        return np.where(count > 0, count * self.d[np.where(count > MOST_DISCOUNTED, 0, count)] / self.scale, self.unknown)


def _merge_words(table):
    words = [np.frombuffer(b, "<u8") for b in table.column("words").to_pylist()]
    counts = [unplaned(b, "<u4") for b in table.column("counts").to_pylist()]
    different, inverse = np.unique(np.concatenate(words), return_inverse=True)
    total = np.bincount(inverse, np.concatenate(counts), len(different)).astype(np.int64)
    cut = np.cumsum([0] + [len(w) for w in words])
    told = np.where(np.bincount(inverse) == 1, -1 - total, total)
    rows = [("answer", c, b, planes(told[inverse[x:y]]), None, None) for c, b, x, y in zip(table.column("chunk").to_pylist(), table.column("part").to_pylist(), cut[:-1], cut[1:], strict=True)]
    seen = total > 0
    freq = np.bincount(total[seen & (total <= MOST_DISCOUNTED + 1)], minlength=MOST_DISCOUNTED + 2)
    part = table.column("part")[0].as_py()
    rows.append(("stats", -1, part, None, None, [int(total.sum()), int(seen.sum()), *freq[1:].tolist()]))
    rows.append(("table", -1, part, different[seen].tobytes(), planes(total[seen]), None))
    return pa.Table.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.string(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.int64())))], ["kind", "chunk", "part", "p1", "p2", "stats"])


def _merge_pairs(table, words):
    get = lambda c, f: [f(b) for b in table.column(c).to_pylist()]
    ctx, lens = get("ctx", lambda b: np.frombuffer(b, "<u8")), get("lens", lambda b: unplaned(b, "<u4"))
    flags, cur = get("flags", lambda b: np.frombuffer(b, np.uint8)), get("cur", unshort)
    cur_count, counts = get("cur_count", lambda b: unplaned(b, "<i8")), get("counts", lambda b: unplaned(b, "<u4"))
    all_ctx, all_cur = np.concatenate(ctx), np.concatenate(cur)
    context, of = np.unique(all_ctx, return_inverse=True)
    of_pair = np.repeat(of, np.concatenate(lens))
    _, example, inverse = np.unique(mix(context[of_pair] ^ mix(all_cur * _G(0x9E3779B97F4A7C15))), return_index=True, return_inverse=True)
    total = np.bincount(inverse, np.concatenate(counts), len(example)).astype(np.int64)
    owner, lower = of_pair[example], words.p(np.concatenate(cur_count)[example])
    seen = total > 0
    n = np.stack([np.bincount(owner[total == r], minlength=len(context)) for r in range(1, MOST_DISCOUNTED + 1)], 1)
    q = np.bincount(owner[seen], lower[seen], len(context))
    rows = []
    cut, ccut = np.cumsum([0] + [len(x) for x in cur]), np.cumsum([0] + [len(x) for x in ctx])
    for k, (c, b) in enumerate(zip(table.column("chunk").to_pylist(), table.column("part").to_pylist(), strict=True)):
        mine = of[ccut[k] : ccut[k + 1]]
        asked = mine[(flags[k] & 1) == 1]
        plain = (n[mine].sum(1) == 0).astype(np.uint8).tobytes()
        more = planes(n[asked].astype(np.int64).ravel()) if len(asked) else b""
        rows.append(("answer", c, b, planes(total[inverse[cut[k] : cut[k + 1]]]), plain, more + q[asked].tobytes(), len(asked), None, None, None))
    freq = np.bincount(total[seen & (total <= MOST_DISCOUNTED + 1)], minlength=MOST_DISCOUNTED + 2)[1:]
    for b in table.column("local").to_pylist():
        freq = freq + (np.frombuffer(b, "<i8") if b else 0)
    part = table.column("part")[0].as_py()
    rows.append(("stats", -1, part, None, None, None, 0, None, freq.tolist(), None))
    hot = np.zeros(len(context), bool)
    hot[of[(np.concatenate(flags) & 2) == 2]] = True
    for h in np.flatnonzero(hot):
        rows.append(("hot", -1, part, None, None, None, 0, int(context[h].view(np.int64)), n[h].tolist(), float(q[h])))
    kinds = (pa.string(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.float64())
    return pa.Table.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], ["kind", "chunk", "part", "p1", "p2", "p3", "asked", "ctx", "stats", "q"])


def _score_chunk(chunk: Chunk, words: Words, d: np.ndarray, hot: dict, answers: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """n_known, base and score of the chunk's documents."""
    count = chunk.count
    base = np.log10((count + 1) / (words.total + words.different + 1))
    p1 = words.p(count)
    bow = np.ones(len(count))
    plain = np.zeros(len(count), bool)
    pair_count = np.zeros(int(chunk.pair.max()) + 1, np.int64)
    r = np.arange(1, MOST_DISCOUNTED + 1)
    for b in chunk.asked_parts:
        c1, c2, c3, asked = answers[int(b)]
        a, z, u, _, _ = chunk.contexts(b)
        pair_count[chunk.asked[a:z]] = unplaned(c1, "<i8")
        plain[u] = np.frombuffer(c2, np.uint8) == 1
        held = u[chunk.pair_held[u]]
        n = unplaned(c3[: asked * MOST_DISCOUNTED * 8], "<i8").reshape(-1, MOST_DISCOUNTED) if asked else np.zeros((0, MOST_DISCOUNTED))
        bow[held] = _backoff(n, np.frombuffer(c3[asked * MOST_DISCOUNTED * 8 :], "<f8"), count[held], d, r)
    if len(chunk.local):
        c, u = chunk.local_count, chunk.local_u
        pair_count[chunk.local] = c
        mine = np.unique(u)
        n = np.stack([np.bincount(u[c == k], minlength=len(count)) for k in r], 1)[mine]
        q = np.bincount(u[c > 0], p1[chunk.local_v[c > 0]], len(count))[mine]
        plain[mine] = n.sum(1) == 0
        bow[mine] = _backoff(n, q, count[mine], d, r)
    for w in np.flatnonzero(np.isin(chunk.words.view(np.int64), np.fromiter(hot, np.int64, len(hot)))):
        n, q = hot[int(chunk.words[w].view(np.int64))]
        plain[w] = sum(n) == 0
        bow[w] = _backoff(np.array([n]), np.array([q]), count[w : w + 1], d, r)[0]
    c = pair_count[chunk.pair]
    u = chunk.before
    whole = np.maximum(count[u] + plain[u], 1)
    p = np.where(c > 0, c * d[np.where(c > MOST_DISCOUNTED, 0, c)] / whole, bow[u] * p1[chunk.token])
    add = lambda x: np.add.reduceat(x, chunk.begin)
    return add((count > 0)[chunk.token].astype(np.int64)), add(base[chunk.token]), add(np.log10(p))


def _backoff(n, q, count, d, r) -> np.ndarray:
    """bow of contexts from the counts of their pairs of each low count, and the lower probability of all their seen words."""
    plain = n.sum(1) == 0
    left = np.where(plain, 1.0, (n * (r * (1 - d[1:]))).sum(1)) / np.maximum(count + plain, 1)
    return left / np.maximum(1 - q, 1e-300)


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", held: Column | None = None) -> DataFrame:
    """One row per row of docs: id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10 of the model's probability).

    Learns from the rows that are not held out.  Null texts are empty and have the end as their one token; rows repeated are counted
    and scored as often as they stand there.  Without training rows every token has probability 1.
    """
    spark = docs.sparkSession
    held = held_out(F.col(id_col)) if held is None else held
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(held, F.lit(False)).alias("held"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    size = rows.agg(F.sum(F.octet_length("text") + 1)).first()[0] or 0
    chunks, parts = max(width(spark), -(-size // CHUNK_BYTES)), max(width(spark), -(-size // PART_BYTES))
    keyed = rows.withColumn("chunk", F.pmod(F.xxhash64("id", F.substring("text", 1, 64), F.octet_length("text")), F.lit(chunks)))
    kind = rows.schema["id"].dataType.simpleString()

    def pack(batches):
        # Texts are moved three times: packed they take two thirds of what Spark's own compression leaves.
        for batch in batches:
            packed = pa.array((zlib.compress(t.as_py().encode(), 1) for t in batch.column("text")), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("held"), batch.column("chunk"), packed], ["id", "held", "chunk", "packed"])

    dealt = keyed.select("id", "held", "chunk", "text").mapInArrow(pack, f"id {kind}, held boolean, chunk bigint, packed binary")

    def ask_words(key, table):
        got = list(Chunk(table, parts).word_requests())
        trim()
        c = key[0].as_py()
        return pa.Table.from_arrays([pa.array([c] * len(got), pa.int64()), pa.array([g[0] for g in got], pa.int32()), pa.array([g[1] for g in got], pa.binary()), pa.array([g[2] for g in got], pa.binary())], ["chunk", "part", "words", "counts"])

    def merge_words(table):
        trim()
        return _merge_words(table)

    def merge_pairs(table):
        trim()
        return _merge_pairs(table, words)

    asked = dealt.groupBy("chunk").applyInArrow(ask_words, "chunk bigint, part int, words binary, counts binary")
    merged = "kind string, chunk bigint, part int, p1 binary, p2 binary, stats array<bigint>"
    word_table = store(asked.groupBy("part").applyInArrow(merge_words, merged), "katz-words")
    stats = [x or 0 for x in word_table.filter("kind = 'stats'").agg(*[F.sum(F.col("stats")[k]) for k in range(MOST_DISCOUNTED + 3)]).first()]
    words = Words(stats[0], stats[1], [0, *stats[2:]])
    release(spark)
    hot_from = stats[0] / (4 * parts)
    word_answers = word_table.filter("kind = 'answer'").select("chunk", "part", "p1")

    def ask_pairs(key, left, right):
        names = ["chunk", "part", "ctx", "lens", "flags", "cur", "cur_count", "counts", "local"]
        got = []
        if left.num_rows:
            chunk = Chunk(left, parts)
            chunk.take_counts(dict(zip(right.column("part").to_pylist(), right.column("p1").to_pylist(), strict=True)))
            chunk.pairs(hot_from)
            got = list(chunk.pair_requests())
        trim()
        c = key[0].as_py()
        local = [chunk.local_frequencies()] + [None] * (len(got) - 1) if got else []
        return pa.Table.from_arrays([pa.array([c] * len(got), pa.int64()), pa.array([g[0] for g in got], pa.int32()), *[pa.array([g[k] for g in got], pa.binary()) for k in range(1, 7)], pa.array(local, pa.binary())], names)

    pairs = dealt.groupBy("chunk").cogroup(word_answers.groupBy("chunk")).applyInArrow(ask_pairs, "chunk bigint, part int, ctx binary, lens binary, flags binary, cur binary, cur_count binary, counts binary, local binary")
    merged = "kind string, chunk bigint, part int, p1 binary, p2 binary, p3 binary, asked bigint, ctx bigint, stats array<bigint>, q double"
    pair_table = store(pairs.groupBy("part").applyInArrow(merge_pairs, merged), "katz-pairs")
    freq = [x or 0 for x in pair_table.filter("kind = 'stats'").agg(*[F.sum(F.col("stats")[k]) for k in range(MOST_DISCOUNTED + 1)]).first()]
    d = discounts([0, *freq])
    # At most 4 * parts contexts have so many of the tokens.
    tops = pair_table.filter("kind = 'hot'").groupBy("ctx").agg(*[F.sum(F.col("stats")[k]).alias(f"n{k}") for k in range(MOST_DISCOUNTED)], F.sum("q").alias("q")).collect()
    hot = spark.sparkContext.broadcast({t.ctx: ([t[f"n{k}"] for k in range(MOST_DISCOUNTED)], t.q) for t in tops})
    release(spark)
    level = lambda df, k: df.select("chunk", "part", F.lit(k).alias("level"), "p1", *[(F.col(c) if k == 2 else F.lit(None).cast(t)).alias(c) for c, t in (("p2", "binary"), ("p3", "binary"), ("asked", "bigint"))])
    answers = level(word_answers, 1).union(level(pair_table.filter("kind = 'answer'"), 2))

    def finish(left, right):
        names = ["id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
        types = (pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
        if not left.num_rows:
            return pa.Table.from_arrays([left.column("id"), *[pa.array([], t) for t in types]], names)
        chunk = Chunk(left, parts)
        got = right.to_pylist()
        chunk.take_counts({g["part"]: g["p1"] for g in got if g["level"] == 1})
        chunk.pairs(hot_from)
        known, base, total = _score_chunk(chunk, words, d, hot.value, {g["part"]: (g["p1"], g["p2"], g["p3"], g["asked"]) for g in got if g["level"] == 2})
        trim()
        columns = (chunk.held, chunk.sizes, known, np.full(chunk.n, words.total), base, total)
        return pa.Table.from_arrays([left.column("id"), *[pa.array(x, t) for x, t in zip(columns, types, strict=True)]], names)

    scored = dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(finish, f"id {kind}, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")
    return scored.withColumnRenamed("id", id_col)

"""Near duplicates by order MinHash, verified by banded alignment.

A text's k-mers are runs of K words; the n-th occurrence of a k-mer counts as one of its own.  A sketch takes the PICKS smallest of
them under its own hash and keeps them in the order they have in the text, so texts share a sketch in so far as they
share k-mers in the same order.  Short texts have exact keys besides.  Texts that share a key are compared by edit similarity over words:
1 - distance / length of the longer text, with the distance from an alignment in a band.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hashed_words, mix, pieces, release, store, trim, whole_numbers
from .components import components

K, PICKS, SKETCHES, SIMILARITY = 3, 2, 40, 0.8
#: Texts of up to TINY words share a key whenever they are one edit apart; those of up to SHORT words, whenever they share a run of K words.
TINY, SHORT = 9, 19
#: Members of a bucket that one task compares with as many.
BLOCK = 4096
#: Members that each one meets in the rounds before the last.
NEAREST = 4
#: Places of a text's word counts: the power of two from its number of words on, between these.
FEWEST_BINS, MOST_BINS = 64, 4096
#: Diagonals of the first band to either side; texts aligned by whole columns; bits of a band above which words are looked up row by row.
BAND, WHOLE, WIDE = 64, 600, 1 << 15
_G = np.uint64


def sketch_texts(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per text: two 64-bit hashes of its word sequence, its number of words, and its SKETCHES order-MinHash values.

    A text of fewer than K words is one k-mer; an empty text has the sketches of no k-mer.
    """
    words, first = hashed_words(column)
    sizes = np.diff(first)
    n = len(sizes)
    owner = np.repeat(np.arange(n), sizes)
    place = (np.arange(len(words)) - first[:-1][owner]).astype(np.uint64)
    whole = np.zeros((n, 2), np.uint64)
    full = np.flatnonzero(sizes)
    for k in (0, 1):
        if len(words):
            whole[full, k] = np.add.reduceat(mix(words + mix(place * _G(2) + _G(k + 1))), first[:-1][full])
    whole = mix(whole + sizes.astype(np.uint64)[:, None])
    # K-mers, the last of a text where K words are left (or its first word if it is shorter).
    counts = np.where(sizes >= K, sizes - K + 1, np.minimum(sizes, 1))
    begin = np.cumsum(counts) - counts
    of = np.repeat(np.arange(n), counts)
    at = np.arange(len(of)) - begin[of] + first[:-1][of]
    kmer = np.zeros(len(of), np.uint64)
    for j in range(K):
        inside = at + j < first[1:][of]
        kmer[inside] += mix(words[at[inside] + j] + _G(j * 2 + 1))
    kmer = mix(kmer)
    key = kmer ^ mix(of.astype(np.uint64) + _G(7))
    order = np.argsort(key, kind="stable")
    # The occurrence goes into every k-mer, repeated or not, so that a text's sketches do not depend on the texts beside it.
    run = np.flatnonzero(np.append(True, key[order][1:] != key[order][:-1])[: len(key)])
    seen = np.empty(len(key), np.int64)
    seen[order] = np.arange(len(key)) - np.repeat(run, np.diff(np.append(run, len(key))))
    kmer = mix(kmer + seen.astype(np.uint64) * _G(0x9E3779B97F4A7C15))
    out = np.zeros((n, SKETCHES), np.uint64)
    full = np.flatnonzero(counts)
    top = _G(0xFFFFFFFFFFFFFFFF)
    for s in range(SKETCHES):
        v = (kmer ^ mix(np.array([s + 101], np.uint64))) * _G(0xD6E8FEB86659FD93)
        v ^= v >> _G(32)
        v *= _G(0xD6E8FEB86659FD93)
        v >>= _G(1)
        spots = np.full((n, PICKS), -1, np.int64)
        for p in range(PICKS):
            live = full[counts[full] > p]
            if not len(live):
                break
            least = np.zeros(n, np.uint64)
            least[full] = np.minimum.reduceat(v, begin[full])
            hit = np.flatnonzero(v == least[of])
            lead = np.append(True, of[hit][1:] != of[hit][:-1])
            hit = hit[lead]
            hit = hit[counts[of[hit]] > p]
            spots[of[hit], p] = hit
            v[hit] = top
        spots.sort(axis=1)
        h = np.full(n, s * 7919 + 1, np.uint64)
        for p in range(PICKS):
            h = mix(h * _G(31) + np.where(spots[:, p] >= 0, kmer[np.maximum(spots[:, p], 0)] if len(kmer) else _G(0), _G(p)))
        out[:, s] = h
    return whole, sizes, out


def short_keys(words: np.ndarray) -> list[int]:
    """Keys by which a text of up to SHORT words meets every text of at least SIMILARITY that is no longer than SHORT.

    Of two such texts the longer has n words.  For n up to TINY one edit is allowed, and the texts agree, each with at most one word left out.
    Above, floor(n / 5) edits leave four fifths of n words in floor(n / 5) + 1 runs at most, one of which has K words.
    The shorter then has TINY - 1 words at least.
    """
    n = len(words)
    if not 0 < n <= SHORT:
        return []
    forms = []
    if n <= TINY:
        forms += [(1, words)] + [(1, np.delete(words, i)) for i in range(n) if n > 1]
    if n >= TINY - 1:
        forms += [(2, words[i : i + K]) for i in range(n - K + 1)]
    out = set()
    for kind, part in forms:
        place = np.arange(len(part), dtype=np.uint64)
        out.add(int(mix(np.array([mix(part + mix(place * _G(2) + _G(1))).sum() + _G(kind)], np.uint64)).view(np.int64)[0]))
    return sorted(out)


def edit_distances(pairs: list[tuple[np.ndarray, np.ndarray]], most: list[int]) -> list[int]:
    """Exact edit distance of each pair of word sequences, or -1 if it is above the pair's limit.

    Ends that agree are cut off; the words that one text has more of than the other bound the distance from below.  The rest is
    aligned in a band around the diagonal that grows until the distance fits in it or the limit is passed.
    """
    out = []
    for (x, y), limit in zip(pairs, most, strict=True):
        short = min(len(x), len(y))
        differ = np.flatnonzero(x[:short] != y[:short])
        cut = int(differ[0]) if len(differ) else short
        x, y = x[cut:], y[cut:]
        short -= cut
        differ = np.flatnonzero(x[len(x) - short :][::-1] != y[len(y) - short :][::-1])
        cut = int(differ[0]) if len(differ) else short
        x, y = x[: len(x) - cut], y[: len(y) - cut]
        if not len(x) or not len(y):
            out.append(len(x) + len(y) if len(x) + len(y) <= limit else -1)
            continue
        codes = np.unique(np.concatenate([x, y]), return_inverse=True)[1]
        a, b = codes[: len(x)], codes[len(x) :]
        counts = np.bincount(a, minlength=codes.max() + 1) - np.bincount(b, minlength=codes.max() + 1)
        fits = max(counts[counts > 0].sum(), -counts[counts < 0].sum()) <= limit
        out.append(_aligned(a, b, limit) if fits else -1)
    return out


def _aligned(x: np.ndarray, y: np.ndarray, most: int) -> int:
    """Short texts by whole columns, longer ones in a band of BAND diagonals to either side, then four times as many, up to the limit."""
    if len(x) < len(y):
        x, y = y, x
    band = max(BAND, len(x) - len(y))
    while True:
        k = min(band, most)
        if len(x) <= max(WHOLE, 2 * k + 2):
            return _columns(x.tolist(), y.tolist(), most)
        found = _banded(x, y, k)
        if found >= 0 or k == most:
            return found
        band *= 4


def _columns(x: list[int], y: list[int], most: int) -> int:
    """Distance by columns of the alignment's table, each a whole number whose bits say where its values step up or down.

    Such bit-parallel columns are due to Myers (1999).  Stops where the last row can't come back under the limit.
    """
    places: dict[int, int] = {}
    for i, c in enumerate(x):
        places[c] = places.get(c, 0) | 1 << i
    every, last = (1 << len(x)) - 1, 1 << (len(x) - 1)
    up, down, score, left = every, 0, len(x), len(y)
    for c in y:
        eq = places.get(c, 0)
        zero = (((eq & up) + up) ^ up) | eq | down
        more, less = down | (every & ~(zero | up)), zero & up
        left -= 1
        if more & last:
            score += 1
            if score - left > most:
                return -1
        elif less & last:
            score -= 1
        more = more << 1 | 1
        up, down = (less << 1 | ~(zero | more)) & every, more & zero & every
    return score if score <= most else -1


def _banded(x: np.ndarray, y: np.ndarray, most: int) -> int:
    """Distance along a band of most diagonals on either side, after Hyyro (2003), for len(x) > 2 * most + 2; -1 above most.

    The column's bits move down one row with each word of y.  Where a word stands in x is kept for a stretch of rows; bands of over WIDE
    bits look it up row by row instead, so memory follows the texts.  Stops once the band's lower edge, and later the last row, is past the limit for good.
    """
    m, n = len(x), len(y)
    width = 2 * most + 2
    every, top = (1 << width) - 1, 1 << (width - 1)
    up, down, score = every ^ ((1 << (width - most - 1)) - 1), 0, most
    at, turn, edge = most + 1 - width, m - most, top >> 1
    base, places = None, {}
    if width > WIDE:
        order = np.argsort(x, kind="stable")
        ranked = x[order]
    for j, c in enumerate(y.tolist()):
        if width > WIDE:
            rows = order[np.searchsorted(ranked, c) : np.searchsorted(ranked, c, side="right")] - at
            rows = rows[(rows >= 0) & (rows < width)]
            bits = np.zeros(width, np.uint8)
            bits[rows] = 1
            eq = int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little") if len(rows) else 0
        else:
            if base is None or at - base > width:
                base, places = at, {}
                for i, w in enumerate(x[max(at, 0) : max(at + 2 * width + 1, 0)].tolist(), max(at, 0) - at):
                    places[w] = places.get(w, 0) | 1 << i
            eq = places.get(c, 0) >> (at - base) & every
        zero = ((((eq & up) + up) ^ up) | eq | down) & every
        more, less = down | (every & ~(zero | up)), zero & up
        if j < turn:
            score += not zero & top
            # On the edge's diagonal nothing falls; from its end at most the words that are left can be won back.
            if score - (n - turn) > most:
                return -1
        else:
            score += 1 if more & edge else -1 if less & edge else 0
            edge >>= 1
            if score - (n - 1 - j) > most:
                return -1
        half = zero >> 1
        up, down = less | (every & ~(half | more)), half & more
        at += 1
    return score if score <= most else -1


def similarity_at_least(x: np.ndarray, y: np.ndarray, least: float) -> int:
    """The distance up to which two sequences are that similar."""
    return int(np.floor((1 - least) * max(len(x), len(y)) + 1e-9))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = SIMILARITY) -> DataFrame:
    """One row per row of docs: id, class_id (largest id of its class), kept (it is that id), n_words.

    Texts with the same words (A-Z lower-cased) are one class from the start and go on as one representative.
    Representatives that share a key are candidates: every pair of them is verified, ruled out by a bound that is never above the distance, or in one
    class already (see linked).  Verified pairs are links, and classes are the connected components.  Words are compared as hashes of 32 bits.

    Ids are whole numbers (others raise TypeError).  Null texts are empty, and all empty texts one class.  Rows with a
    null id join the class of an equal text with an id, or have a null class.  Rows with one id and different texts share their class.
    """
    whole_numbers(docs, id_col)
    kind = "bigint"
    rows = docs.select(F.col(id_col).cast(kind).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))

    def run(batches):
        for whole in batches:
            for batch in pieces(whole, "text", 500_000):
                sig, sizes, sketches = sketch_texts(batch.column("text"))
                signed = sketches.view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(sizes) + 1) * SKETCHES, pa.int32()), pa.array(signed.ravel(), pa.int64()))
                words, first = hashed_words(batch.column("text"))
                short = [short_keys(words[a:b]) if b - a <= SHORT else [] for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(sizes, pa.int64()), pa.array(sig[:, 0].copy().view(np.int64) if len(sig) else [], pa.int64()), pa.array(sig[:, 1].copy().view(np.int64) if len(sig) else [], pa.int64()), lists, pa.array(short, pa.list_(pa.int64()))], ["id", "n_words", "sig1", "sig2", "sketches", "short"])

    sketched = store(rows.mapInArrow(run, "id bigint, n_words bigint, sig1 bigint, sig2 bigint, sketches array<bigint>, short array<bigint>"), "near-sketches")
    same = sketched.groupBy("sig1", "sig2").agg(F.max("id").alias("rep"), F.first("sketches").alias("sketches"), F.first("short").alias("short"), F.first("n_words").alias("n"))
    same = store(same, "near-classes")
    single = F.expr("transform(sketches, (x, i) -> xxhash64(x, i))")
    keys = same.filter("n > 0 and rep is not null").select("rep", "n", F.explode(F.concat(single, F.coalesce("short", F.array().cast("array<bigint>")))).alias("key"))
    leaders = keys.groupBy("key").agg(F.max(F.struct("rep", "n")).alias("l"), F.count(F.lit(1)).alias("c")).filter("c > 1").select("key", F.col("l.rep").alias("leader"), F.col("l.n").alias("leader_n"), "c")
    of = linked(rows, store(keys.join(leaders, "key"), "near-keys"), least)
    joined = sketched.join(same.select("sig1", "sig2", "rep"), ["sig1", "sig2"]).join(of, F.col("rep") == F.col("node"), "left")
    class_id = F.coalesce("component", "rep")
    return joined.select(F.col("id").alias(id_col), class_id.alias("class_id"), F.col("id").eqNullSafe(class_id).alias("kept"), "n_words")


def linked(rows: DataFrame, shared: DataFrame, least: float) -> DataFrame:
    """node, component of the representatives of shared (key, rep, n, leader, leader_n, c) that are linked to another one.

    First every member of a bucket of c meets its leader.  Then members of buckets that hold several classes meet, block
    by block of the bucket, those NEAREST to them by word counts, twice, and at last all those that are not in their class; in blocks only pairs go on that
    pass the bounds of length and of word counts.  So a bucket of like texts ends early, one of unlike texts that have a passage in common makes few pairs,
    texts about as alike as the threshold are one class before all their pairs are due, and no pair that can be a new link is left out.
    """
    words = words_of(rows, shared.select(F.col("rep").alias("id")).distinct())
    tested = store(shared.filter((F.col("rep") != F.col("leader")) & (F.least("n", "leader_n") >= least * F.greatest("n", "leader_n") - 1e-6)).select("rep", "leader").distinct(), "near-pairs")
    of = components(store(pairs_verified(words, tested, least), "near-links"))
    again = None
    for nearest in (NEAREST, NEAREST, None):
        # Buckets of two have had their only pair, and after a round of the nearest those that had no more are done.
        rest = shared.filter("c > 2") if again is None else shared.join(again, "key", "left_semi")
        rest = rest.join(of, F.col("rep") == F.col("node"), "left").select("key", "rep", "n", F.coalesce("component", "rep").alias("part"))
        mixed = store(rest.groupBy("key").agg(F.min("part").alias("low"), F.max("part").alias("high"), F.count(F.lit(1)).alias("c")).filter("low <> high").select("key", "c"), "near-mixed")
        rest = store(rest.join(mixed, "key"), "near-open")
        if rest.isEmpty():
            break
        met = store(block_pairs(rest, words, least, nearest), "near-met")
        pairs = met.select(F.least("rep", "head").alias("rep"), F.greatest("rep", "head").alias("leader")).distinct()
        pairs = store(pairs.join(tested.select(F.least("rep", "leader").alias("rep"), F.greatest("rep", "leader").alias("leader")), ["rep", "leader"], "left_anti"), "near-pairs")
        tested = tested.union(pairs)
        of = merged(of, store(pairs_verified(words, pairs, least), "near-links"))
        again = store(met.filter("more").select("key").distinct(), "near-more")
        release(rows.sparkSession, rest)
    return of


def merged(of: DataFrame, links: DataFrame) -> DataFrame:
    """node, component after further links (a, b): only classes that they join are gone through again."""
    part = lambda c: of.select(F.col("node").alias(c), F.col("component").alias(f"{c}_part"))
    ends = links.join(part("a"), "a", "left").join(part("b"), "b", "left")
    between = ends.select(F.coalesce("a_part", "a").alias("a"), F.coalesce("b_part", "b").alias("b")).filter("a <> b").distinct()
    joined = components(between)
    known = of.join(joined.select(F.col("node").alias("component"), F.col("component").alias("over")), "component", "left").select("node", F.coalesce("over", "component").alias("component"))
    return store(known.union(joined.join(of, "node", "left_anti")), "near-classes")


def block_pairs(rest: DataFrame, words: DataFrame, least: float, nearest: int | None = None) -> DataFrame:
    """key, rep, head, more: all pairs of members of a bucket that are in different classes and pass the bounds; with nearest, so many of each member's with the closest word counts.

    more: this member has further ones.  A bucket without such a member has given all its pairs.
    A pair that meets in several of the buckets is given by the one with the lowest key: members bring their lower keys.

    A bucket is dealt into blocks of about BLOCK members by a hash; two blocks, or one with itself, meet in one place, where a group holds no more
    than two blocks.  Members are compared by counts of their words in hashed places: what one has more of is no more than the distance.
    """
    # Counts are joined once for each member, whose buckets are as many as it has keys.
    members = rest.groupBy("rep").agg(F.first("n").alias("n"), F.first("part").alias("part"), F.collect_list(F.struct("key", F.ceil(F.col("c") / BLOCK).cast("int").alias("blocks"))).alias("keys"))
    filled = members.join(words.select(F.col("id").alias("rep"), "bins"), "rep").withColumn("drawn", F.hash("rep", F.lit("block")))
    lower = "transform(filter(keys, x -> x.key < k.key), x -> x.key) as lower"
    meetings = F.expr(f"flatten(transform(keys, k -> transform(sequence(0, k.blocks - 1), o -> struct(k.key as key, pmod(drawn, k.blocks) as own, o as other, {lower}))))")
    dealt = filled.select("rep", "n", "part", "bins", F.explode(meetings).alias("m"))
    filled = dealt.select("m.key", F.least("m.own", "m.other").alias("lo"), F.greatest("m.own", "m.other").alias("hi"), "m.own", "rep", "n", "part", "bins", "m.lower")
    names = ["key", "lo", "hi", "own", "rep", "n", "part", "bins", "lower"]

    def meet(batches):
        held = None
        for batch in batches:
            rows = pa.Table.from_batches([batch]).select(names)
            rows = pa.concat_tables([held, rows]).combine_chunks() if held is not None else rows
            groups = np.stack([rows.column(c).to_numpy() for c in ("key", "lo", "hi")])
            cuts = np.append(np.flatnonzero(np.append(True, (groups[:, 1:] != groups[:, :-1]).any(axis=0))), rows.num_rows)
            for a, z in zip(cuts[:-2], cuts[1:-1], strict=True):
                yield from met(rows.slice(a, z - a))
            held = rows.slice(cuts[-2]) if rows.num_rows else None
        if held is not None:
            yield from met(held)

    def met(group):
        rep, n, part, own = (group.column(c).to_numpy() for c in ("rep", "n", "part", "own"))
        bins = [np.frombuffer(b, np.uint8) for b in group.column("bins").to_pylist()]
        keys = group.column("lower").combine_chunks()
        lower = np.split(keys.flatten().to_numpy(), np.cumsum(keys.value_lengths().to_numpy())[:-1])
        first, second, more = count_pairs(n, part, own, bins, least, nearest, lower)
        for at in range(0, len(first), 50_000):
            some = slice(at, at + 50_000)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first[some]), group.column("key")[0].as_py())), pa.array(rep[first[some]]), pa.array(rep[second[some]]), pa.array(more[some])], ["key", "rep", "head", "more"])

    placed = filled.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi")
    return placed.mapInArrow(meet, "key bigint, rep bigint, head bigint, more boolean")


def count_pairs(n: np.ndarray, part: np.ndarray, own: np.ndarray, bins: list[np.ndarray], least: float, nearest: int | None = None, lower: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of the pairs in different parts, of different blocks where there are two, without a common key in lower, whose lengths and word counts allow the similarity.

    With nearest, at most so many of those in which a member is the shorter one, and whether it has more of them.
    """
    holders = holders_of(lower) if lower is not None else [[]] * len(n)
    order = np.argsort(n, kind="stable")
    two = own.min() != own.max()
    sizes = np.array([len(bins[i]) for i in order])
    found: tuple[list, list, list] = ([], [], [])
    # Of two texts the longer has as many places as the shorter, or more; it is folded to the shorter one's.
    for size in np.unique(sizes):
        reach = np.flatnonzero(sizes >= size)
        table = np.stack([np.minimum(bins[order[i]].reshape(-1, size).sum(axis=0, dtype=np.uint32), 255).astype(np.uint8) for i in reach])
        total = table.sum(axis=1, dtype=np.int64)
        place, length, classes, block = order[reach], n[order[reach]], part[order[reach]], own[order[reach]]
        ends = np.searchsorted(length, np.floor(length / least + 1e-6), side="right")
        for i in np.flatnonzero(sizes[reach] == size):
            # Texts as long as this one or longer stand behind it.
            near = np.arange(i + 1, ends[i])
            near = near[(classes[near] != classes[i]) & ((block[near] != block[i]) if two else True)]
            if len(near) and holders[place[i]]:
                elsewhere = np.zeros(len(n), bool)
                for some in holders[place[i]]:
                    elsewhere[some] = True
                near = near[~elsewhere[place[near]]]
            if len(near):
                common = np.minimum(table[near], table[i]).sum(axis=1, dtype=np.uint32)
                apart = np.maximum(total[near], total[i]) - common
                fits = apart <= np.floor((1 - least) * length[near] + 1e-9)
                ok = near[fits]
                more = bool(nearest) and len(ok) > nearest
                if more:
                    ok = ok[np.argsort(apart[fits] / length[ok], kind="stable")[:nearest]]
                found[0].append(np.full(len(ok), place[i]))
                found[1].append(place[ok])
                found[2].append(np.full(len(ok), more))
    return tuple(np.concatenate(f).astype(kind) if f else np.zeros(0, kind) for f, kind in zip(found, (np.int64, np.int64, bool), strict=True))


def holders_of(keys: list[np.ndarray]) -> list[list[np.ndarray]]:
    """For each list of keys: of every key that others have too, the places of all lists that hold it."""
    sizes = [len(k) for k in keys]
    number = np.unique(np.concatenate(keys), return_inverse=True)[1]
    owner = np.repeat(np.arange(len(keys)), sizes)
    by = np.argsort(number, kind="stable")
    held = np.split(owner[by], np.cumsum(np.bincount(number))[:-1]) if len(number) else []
    return [[held[k] for k in own if len(held[k]) > 1] for own in np.split(number, np.cumsum(sizes)[:-1])]


def word_bins(words: np.ndarray) -> bytes:
    """How often words fall into each of a power of two of places, up to 255."""
    size = FEWEST_BINS
    while size < min(len(words), MOST_BINS):
        size *= 2
    return np.minimum(np.bincount(words % size, minlength=size), 255).astype(np.uint8).tobytes()


def words_of(rows: DataFrame, need: DataFrame) -> DataFrame:
    """id, words, bins (word_bins) of the rows whose ids stand in need; of rows with one id the longest text counts."""

    def to_words(batches):
        for whole in batches:
            for batch in pieces(whole, "text"):
                words, first = hashed_words(batch.column("text"))
                small = words.astype("<u4")
                texts = [small[a:b] for a, b in zip(first[:-1], first[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([t.tobytes() for t in texts], pa.binary()), pa.array([word_bins(t) for t in texts], pa.binary())], ["id", "words", "bins"])

    # Every size takes the same way: a broadcast of these ids would grow with the corpus.
    wanted = rows.join(need.hint("merge"), "id", "left_semi").mapInArrow(to_words, "id bigint, words binary, bins binary")
    longest = F.max_by(F.struct("words", "bins"), F.octet_length("words")).alias("w")
    return store(wanted.groupBy("id").agg(longest).select("id", "w.*"), "near-words")


def pairs_verified(words: DataFrame, pairs: DataFrame, least: float) -> DataFrame:
    """Of pairs (rep, leader) of ids of words, those whose texts are similar enough: a, b."""
    left = pairs.join(words.select(F.col("id").alias("rep"), F.col("words").alias("wa")).hint("merge"), "rep")
    # Pairs whose lengths rule out the similarity need no alignment.
    right = words.select(F.col("id").alias("leader"), F.col("words").alias("wb"))
    both = left.join(right.hint("merge"), "leader").filter(F.least(F.octet_length("wa"), F.octet_length("wb")) >= least * F.greatest(F.octet_length("wa"), F.octet_length("wb")) - 4e-6)

    def verify(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 1000):
                part = whole.slice(at, 1000)
                texts = [(np.frombuffer(x, "<u4"), np.frombuffer(y, "<u4")) for x, y in zip(part.column("wa").to_pylist(), part.column("wb").to_pylist(), strict=True)]
                trim()
                found = edit_distances(texts, [similarity_at_least(x, y, least) for x, y in texts])
                keep = pa.array([d >= 0 for d in found])
                yield pa.RecordBatch.from_arrays([part.column("rep").filter(keep), part.column("leader").filter(keep)], ["a", "b"])

    return both.mapInArrow(verify, "a bigint, b bigint")


def keep_near(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay: of every class the one with its largest id, with all their columns.

    Rows with a null id stay, rows repeated stay or go together; null texts are empty, and of all empty texts one stays.  Any names of columns
    will do: a row travels as one value.
    """
    found = near_duplicates(docs, id_col, text_col)
    gone = found.filter(~F.col("kept")).select(F.col(id_col).alias("id")).distinct()
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return whole.join(gone, F.col("row")[id_col] == F.col("id"), "left_anti").select("row.*")

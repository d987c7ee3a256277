"""N-gram Jaccard join with adaptive multi-match prefixes, up to components.

A document is its set of distinct k-word shingles; two link when
100 * |intersection| >= percent * |union|. Steps:

1. Documents with equal sets collapse to a class with a number of its own; classes are the nodes.
2. Shingles are ordered by rarity, from a frequency sketch over all documents whose size follows the
   number of shingles up to a bound, ties by hash: one order for all, which is all that exactness needs.
3. A class with n shingles and T = ceil(n * percent / 100) posts its first n - T + l of them.
   Two linked classes share at least min(l, l') of the shingles both have posted. Each
   class takes the l whose estimated cost (postings met, and candidates met l times to be
   verified) is least, so costly ones post a little more and verify much less.
4. Every posted shingle has a hub, the class of its list with the commonest prefix, as the origin
   of a group of copies has. A class that shares min(l, l') posted shingles or more with a hub is
   verified against it; links give components. So a group of near copies costs its size, not its square.
5. Shingles whose lists still lie in several components are joined with themselves across
   components only, under bounds by size and by position in both prefixes; pairs that share min(l, l')
   prefix shingles are verified. So no link between components is lost.

Shingles are held as 64-bit hashes. Null or blank text: empty set, linked with nothing, but
its component is its own id. Rows that share a doc_id are one node: all their classes are linked. A document
with a null doc_id links others like any other; it gets the component of its class, or null. Extra columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.llm import bloom
from graphcc.llm import words as W
from graphcc.plans.components import connected_components
from graphcc.session import Kept, computed_at_once

#: The sketch has 2**18 cells, and more for a larger corpus (a cell to 2**9 shingles) up to 2**20: 4 MB.
SKETCH_BITS, MOST_SKETCH_BITS, MOST_L, VERIFY_COST = 18, 20, 4, 8.0
#: Shingles of a document counted in so many bins by hash: the sum of bin-wise minima bounds the overlap of two documents.
BINS = 256
#: Classes to fetch are broadcast up to this many (40 bytes each), else joined by a shuffle.
BROADCAST_ROWS = 200_000
_SEED = np.uint64(0xD6E8FEB86659FD93)


def need(n, percent: int):
    """The least overlap a document with n shingles has with any it links to."""
    return -(-n * percent // 100)


def _sets(batch: pa.RecordBatch, k: int):
    for part in W.slices(batch):
        w = W.words(part.column("text"), lower=True)
        yield part, *W.shingle_sets(w, k)


def _sums(s: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums over each set: with its size, the class a document is in."""
    sums = [np.concatenate((np.zeros(1, np.uint64), np.cumsum(x))) for x in (W.mix(s ^ _SEED), W.mix(s * W.LANE[1]))]
    one, two = ((c[at[1:]] - c[at[:-1]]).view(np.int64) for c in sums)
    return one, two


def _signatures(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, s, at in _sets(batch, k):
                one, two = _sums(s, at)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.diff(at)), pa.array(one), pa.array(two)], ["doc_id", "n", "s1", "s2"])

    return run


def _counts(k: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << bits, np.int32)
        for batch in batches:
            for _, s, _ in _sets(batch, k):
                np.add.at(total, (s >> np.uint64(64 - bits)).astype(np.int64), np.int32(1))
        b = np.flatnonzero(total)
        for at in range(0, len(b), 1 << 16):
            part = b[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), pa.array(total[part].astype(np.int64))], ["bucket", "n"])

    return run


def frequency_sketch(docs: DataFrame, k: int, bits: int = SKETCH_BITS) -> np.ndarray:
    """Shingles of all documents counted by the first ``bits`` of their hash: 2**bits numbers, whatever the corpus."""
    per = docs.select("text").mapInArrow(_counts(k, bits), "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    with computed_at_once(docs.sparkSession):
        got = per.toPandas()
    out = np.zeros(1 << bits, np.int32)
    out[got["bucket"].to_numpy(np.int64)] = np.minimum(got["n"].to_numpy(np.int64), 2**31 - 1)
    return out


def sketch_bits_for(shingles: int) -> int:
    """Cells for a corpus with so many shingles, as a power of 2."""
    return min(MOST_SKETCH_BITS, max(SKETCH_BITS, shingles.bit_length() - 9))


def choose_l(excess: np.ndarray, n: int, percent: int, most: int = MOST_L) -> int:
    """The l of least estimated cost, from the expected list lengths of a document's shingles in order."""
    t = need(n, percent)
    base = n - t
    met = np.cumsum(excess[: base + most])
    best, least = 1, np.inf
    for l_ in range(1, min(most, t) + 1):
        cost = float(met[base + l_ - 1]) * (1 + VERIFY_COST / l_)
        if cost < least - 1e-9:
            best, least = l_, cost
    return best


PREFIXES = "id long, s1 long, s2 long, n int, l int, common long, tokens array<long>, bins binary"


def _prefixes(k: int, percent: int, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sketch = shared.value
        bits, noise = len(sketch).bit_length() - 1, int(np.median(sketch))
        for batch in batches:
            for part, s, at in _sets(batch, k):
                one, two = _sums(s, at)
                count = sketch[(s >> np.uint64(64 - bits)).astype(np.int64)]
                bin_of = ((s >> np.uint64(20)) & np.uint64(BINS - 1)).astype(np.int64)
                rows = np.flatnonzero(np.diff(at))
                ls, common, lists, bins = [], [], [np.zeros(0, np.int64)], []
                for a, b in zip(at[rows].tolist(), at[rows + 1].tolist(), strict=True):
                    n = b - a
                    order = np.argsort(count[a:b], kind="stable")  # equal counts stay in hash order
                    excess = np.maximum(count[a:b][order[: n - need(n, percent) + MOST_L]] - noise, 0)
                    l_ = choose_l(excess, n, percent)
                    p = n - need(n, percent) + l_
                    ls.append(l_)
                    common.append(int(excess[: p - l_ + 1].sum()))
                    lists.append(s[a:b][order[:p]].view(np.int64))
                    bins.append(np.minimum(np.bincount(bin_of[a:b], minlength=BINS), 255).astype(np.uint8).tobytes())
                ends = np.cumsum([len(x) for x in lists]).astype(np.int32)
                cols = [
                    part.column("doc_id").take(pa.array(rows)), pa.array(one[rows]), pa.array(two[rows]), pa.array(np.diff(at)[rows].astype(np.int32)), pa.array(ls, pa.int32()),
                    pa.array(common, pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(lists))), pa.array(bins, pa.binary()),
                ]
                yield pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in PREFIXES.split(", ")])

    return run


def _row_keys(ids: pa.Array, one: np.ndarray) -> np.ndarray:
    """A number for a document's id and set, by which a bit set knows it."""
    known = ids.cast(pa.int64()).fill_null(-1).to_numpy(zero_copy_only=False).view(np.uint64)
    return W.mix(known * W.LANE[2] + one.view(np.uint64)).view(np.int64)


def _keys_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([pa.array(_row_keys(b.column("rep"), b.column("s1").to_numpy()))], ["key"])


SETS = "id long, s1 long, s2 long, n int, shingles array<long>"


def _whole_sets(k: int, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = shared.value  # documents that surely stand for no class asked for are left out
        for batch in batches:
            for part, s, at in _sets(batch, k):
                one, two = _sums(s, at)
                size = np.diff(at)
                rows = np.flatnonzero(bloom.holds(_row_keys(part.column("doc_id"), one), mask) & (size > 0))
                if len(rows):
                    ends = np.concatenate(([0], np.cumsum(size[rows]))).astype(np.int32)
                    inside = np.zeros(len(s) + 1, np.int8)
                    inside[at[rows]] += 1
                    inside[at[rows + 1]] -= 1
                    lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(s[np.cumsum(inside[:-1]) > 0].view(np.int64)))
                    cols = [part.column("doc_id").take(pa.array(rows)), *[pa.array(x) for x in (one[rows], two[rows], size[rows].astype(np.int32))], lists]
                    yield pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in SETS.split(", ")])

    return run


def _may_link(percent: int):
    """Pairs whose sizes and bins allow a link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                na, nb = (part.column(c).to_numpy().astype(np.int64) for c in ("na", "nb"))
                x, y = (np.frombuffer(b"".join(part.column(c).to_pylist()), np.uint8).reshape(-1, BINS) for c in ("xa", "xb"))
                bound = np.minimum(x, y).sum(axis=1, dtype=np.int64)
                full = ((x == 255) & (y == 255)).any(axis=1)  # such a bin may hold more than it shows
                bound = np.where(full, np.minimum(na, nb), bound)
                ok = (np.minimum(na, nb) * 100 >= np.maximum(na, nb) * percent) & (bound * 100 >= (na + nb - bound) * percent)
                yield part.select(["a", "b"]).filter(pa.array(ok))

    return run


def _possible(pairs: DataFrame, prefixes: DataFrame, percent: int) -> DataFrame:
    one, two = (prefixes.select(F.col("id").alias(e), F.col("n").alias(f"n{e}"), F.col("bins").alias(f"x{e}")) for e in "ab")
    return pairs.join(one, "a").join(two, "b").select("a", "b", "na", "nb", "xa", "xb").mapInArrow(_may_link(percent), "a long, b long")


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs ``(a, b)`` that link, of those given; ``b`` is the one that many pairs may share."""
    one, two = sets.select(F.col("id").alias("a"), F.col("shingles").alias("sa")), sets.select(F.col("id").alias("b"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    fits = F.least(F.size("sa"), F.size("sb")) * 100 >= F.greatest(F.size("sa"), F.size("sb")) * percent
    return pairs.join(one, "a").join(two, "b").where(fits).where(both * 100 >= (F.size("sa") + F.size("sb") - both) * percent).select("a", "b")


def _of_class(scanned: DataFrame, classes: DataFrame, few: bool = False) -> DataFrame:
    """Scanned rows of the documents that stand for their class, with the class's number as ``id``."""
    stands = classes.select(F.col("cid"), F.col("rep"), F.col("s1").alias("c1"), F.col("s2").alias("c2"), F.col("n").alias("cn"))
    stands = F.broadcast(stands) if few else stands
    same = F.col("id").eqNullSafe(F.col("rep")) & (F.col("s1") == F.col("c1")) & (F.col("s2") == F.col("c2")) & (F.col("n") == F.col("cn"))
    rest = [c for c in scanned.columns if c not in ("id", "s1", "s2")]
    return scanned.join(stands, same).select(F.col("cid").alias("id"), *rest)


def _sets_of(docs: DataFrame, classes: DataFrame, pairs: DataFrame, k: int) -> Kept:
    """``(id, shingles)`` of the classes in ``pairs``; a bit set leaves most other documents out of the scan."""
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("cid")).distinct()
    wanted = Kept(classes.join(wanted, "cid", "left_semi"), "wanted")
    n = wanted.df.count()
    met = docs.sparkSession.sparkContext.broadcast(bloom.build(wanted.df.select("rep", "s1").mapInArrow(_keys_of, "key long"), n))
    found = _of_class(docs.mapInArrow(_whole_sets(k, met), SETS), wanted.df, n <= BROADCAST_ROWS)
    out = Kept(found.groupBy("id").agg(F.first("shingles").alias("shingles")), "sets")
    wanted.drop()
    return out


def _aliases(signed: DataFrame, classes: DataFrame) -> Kept | None:
    """``(doc_id, cid)`` of documents whose rows differ: all their classes are one node; None without such documents."""
    sig = F.struct("n", "s1", "s2")
    several = signed.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min(sig).alias("lo"), F.max(sig).alias("hi")).where("lo <> hi").select("doc_id")
    several = Kept(several, "several")
    if several.df.isEmpty():
        several.drop()
        return None
    return Kept(signed.where("n > 0").join(several.df, "doc_id", "left_semi").join(classes, ["n", "s1", "s2"]).select("doc_id", "cid").distinct(), "aliases")


def _postings(docs: DataFrame, classes: DataFrame, k: int, percent: int, sketch_bits: int | None) -> tuple[Kept, Kept]:
    """Prefixes of all classes, and those postings whose shingle is in several lists, with the list's hub."""
    spark = docs.sparkSession
    shingles = classes.agg(F.sum("n")).first()[0] or 0
    sketch = spark.sparkContext.broadcast(frequency_sketch(docs, k, sketch_bits or sketch_bits_for(shingles)))
    scanned = docs.mapInArrow(_prefixes(k, percent, sketch), PREFIXES)
    prefixes = Kept(_of_class(scanned, classes), "prefixes")
    if not prefixes.df.groupBy("id").count().where("count > 1").isEmpty():  # repeated rows
        once = Kept(prefixes.df.dropDuplicates(["id"]), "prefixes")
        prefixes.drop()
        prefixes = once
    posted = prefixes.df.select("id", "n", "l", "common", F.posexplode("tokens").alias("i", "token"))
    hubs = posted.groupBy("token").agg(F.max_by(F.struct("id", "l"), "common").alias("hub"), F.count(F.lit(1)).alias("c")).where("c > 1")
    shared = posted.join(hubs, "token").select("token", "id", "n", "i", F.col("hub.id").alias("hub"), F.least("l", "hub.l").alias("asked"))
    return prefixes, Kept(shared, "postings")


def _across(shared: DataFrame, found: DataFrame, prefixes: DataFrame, first: DataFrame, percent: int) -> tuple[DataFrame, list[Kept]]:
    """Pairs of classes in different components that share enough of their prefixes, but those in ``first``; tables to drop."""
    placed = shared.join(found.withColumnRenamed("node", "id"), "id", "left").select("token", "id", "n", "i", F.coalesce("component", "id").alias("c"))
    placed = Kept(placed, "placed")
    mixed = placed.df.groupBy("token").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("token")
    left = Kept(placed.df.join(mixed, "token", "left_semi"), "mixed")
    x, y = (left.df.select("token", *[F.col(c).alias(f"{c}{e}") for c in ("id", "n", "i", "c")]) for e in "12")
    # At the first shingle two classes share, both must have enough left for the least overlap of their sizes.
    overlap = F.floor((F.col("n1") + F.col("n2")) * percent / F.lit(100 + percent) + F.lit(1 - 1e-6))  # a ceiling, never too high by rounding
    sizes = F.least("n1", "n2") * 100 >= F.greatest("n1", "n2") * percent
    fits = sizes & (F.least(F.col("n1") - F.col("i1"), F.col("n2") - F.col("i2")) >= overlap)
    pairs = x.join(y, (x["token"] == y["token"]) & (F.col("c1") < F.col("c2")) & fits).select(F.least("id1", "id2").alias("a"), F.greatest("id1", "id2").alias("b")).distinct()
    tried = first.select(F.least("a", "b").alias("t1"), F.greatest("a", "b").alias("t2")).distinct()
    untried = pairs.join(tried, (F.col("a") == F.col("t1")) & (F.col("b") == F.col("t2")), "left_anti")
    one, two = (prefixes.select(F.col("id").alias(e), F.col("l").alias(f"l{e}"), F.col("tokens").alias(f"t{e}")) for e in "ab")
    often = F.size(F.array_intersect("ta", "tb")) >= F.least("la", "lb")
    return untried.join(one, "a").join(two, "b").where(often).select("a", "b"), [placed, left]


def _verified_links(docs: DataFrame, classes: DataFrame, pairs: DataFrame, prefixes: DataFrame, k: int, percent: int) -> Kept:
    """Those of ``pairs`` that link: bounded by sizes and bins first, then by their whole sets."""
    likely = Kept(_possible(pairs, prefixes, percent), "likely")
    if likely.df.isEmpty():
        return likely
    sets = _sets_of(docs, classes, likely.df, k)
    links = Kept(_verified(likely.df, sets.df, percent), "links")
    for t in (likely, sets):
        t.drop()
    return links


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, sketch_bits: int | None = None, tail_rows: int = 10_000) -> DataFrame:
    """``(doc_id, n_shingles, component_id)`` for every row of ``docs(doc_id, text)``."""
    docs = docs.select("doc_id", "text")
    signed = Kept(docs.mapInArrow(_signatures(k), "doc_id long, n long, s1 long, s2 long"), "signatures").df
    grouped = signed.where("n > 0").groupBy("n", "s1", "s2").agg(F.min("doc_id").alias("rep"))
    classes = Kept(grouped.withColumn("cid", F.monotonically_increasing_id()), "classes")
    aliases = _aliases(signed, classes.df)
    prefixes, shared = _postings(docs, classes.df, k, percent, sketch_bits)

    met = shared.df.where("id <> hub").groupBy(F.col("id").alias("a"), F.col("hub").alias("b")).agg(F.count(F.lit(1)).alias("c"), F.max("asked").alias("asked"))
    first = Kept(met.where("c >= asked").select("a", "b"), "candidates")
    links = _verified_links(docs, classes.df, first.df, prefixes.df, k, percent)
    known = links.df
    if aliases:
        known = known.unionByName(aliases.df.join(aliases.df.groupBy("doc_id").agg(F.min("cid").alias("a")), "doc_id").select("a", F.col("cid").alias("b")).where("a <> b"))
    found = Kept(_components(known, tail_rows), "components")

    rest, done = _across(shared.df, found.df, prefixes.df, first.df, percent)
    more = _verified_links(docs, classes.df, rest, prefixes.df, k, percent)
    final = found if more.df.isEmpty() else Kept(_components(known.unionByName(more.df), tail_rows), "components")

    # A component is known by the smallest id of its documents.
    members = final.df.join(classes.df.select(F.col("cid").alias("node"), "rep"), "node")
    least = members.groupBy("component").agg(F.min("rep").alias("label"))
    labels = Kept(members.join(least, "component").select(F.col("node").alias("cid"), "label"), "labels")
    per_class = classes.df.join(labels.df, "cid", "left").select(F.col("n").alias("cn"), F.col("s1").alias("c1"), F.col("s2").alias("c2"), F.coalesce("label", "rep").alias("label"))
    per_class = Kept(per_class, "labels").df
    same = (F.col("n") == F.col("cn")) & (F.col("s1") == F.col("c1")) & (F.col("s2") == F.col("c2"))
    judged = signed.join(per_class, same, "left").select("doc_id", F.col("n").alias("n_shingles"), "label")
    if aliases:  # rows without words get what other rows of their document have
        of_doc = aliases.df.join(classes.df, "cid").join(labels.df, "cid", "left").groupBy(F.col("doc_id").alias("d")).agg(F.min(F.coalesce("label", "rep")).alias("other"))
        judged = judged.join(Kept(of_doc, "documents").df, F.col("doc_id") == F.col("d"), "left").withColumn("label", F.coalesce("label", "other"))
    for t in {*done, prefixes, shared, first, links, more, found, final, classes, labels}:
        t.drop()
    return judged.select("doc_id", "n_shingles", F.coalesce("label", "doc_id").alias("component_id"))


def _components(links: DataFrame, tail_rows: int) -> DataFrame:
    return connected_components(links.select(F.col("a").alias("u"), F.col("b").alias("v")), tail_rows=tail_rows)

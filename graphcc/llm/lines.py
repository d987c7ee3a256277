"""Line dedup by a segment-partition edit join (DataFrame functions only).

A line is dropped if it repeats an earlier line exactly, or lies within ``TAU`` edits of an
earlier one and both have at least ``NEAR_CHARS`` characters. Earlier means a smaller
(doc_id, row, line number). The join over distinct lines:

1. A line of length L is cut into TAU + 1 segments. Two lines within TAU edits share a segment,
   at nearly the same place. Each line is indexed by (L, segment number, segment) and probes,
   for its own length and the TAU lengths below, just the few substrings that a
   left-to-right reading of at most TAU edits allows for each segment.
2. A match must also agree, within what TAU edits can change, in how often ten letters occur; this
   is tested inside the join, so lines grown from one template do not yield all their pairs.
3. Remaining pairs are verified by a banded bit-parallel edit distance: 2 * TAU + 1 cells of
   each column in the bits of one integer.

Lines are told apart by 128 bits of hash. Hot lines are counted on the map side first, and the join back to their occurrences can be split by the planner.

Null text counts as empty. Blank lines and lines under ``EXACT_CHARS`` characters always stay. A null
doc_id sorts first. Rows that share an id, or have none, are documents of their own: they get numbers,
written once with their texts to the shared folder. An empty table gives no rows.
Extra columns pass through ``dedup_lines`` unchanged.

With ``short``, exact repeats of every non-blank line go too, and lines of ``EXACT_CHARS`` characters or more
within ``SHORT_TAU`` edits of an earlier one.
"""

from __future__ import annotations

from decimal import Decimal
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphcc.session import Kept

TAU, NEAR_CHARS, EXACT_CHARS = 2, 32, 6
#: With ``short``, the edits allowed where the shorter line has ``EXACT_CHARS`` to ``NEAR_CHARS`` - 1 characters.
SHORT_TAU = 1
LETTERS = "entharoisd"
#: Ids of lines to fetch are broadcast up to this many (24 bytes each), else joined by shuffle.
BROADCAST_ROWS = 200_000
#: Rows without an id of their own that a place has room to number.
MOST_NUMBERED = 2**32 - 1
_PAD = 8  # bits of a column kept above the band


def probes(tau: int = TAU) -> list[tuple[int, int, int]]:
    """(length difference, segment, shift) of every substring to probe; those with difference and shift 0 are the index entries, first."""
    found = []
    for delta in range(tau + 1):
        for i in range(tau + 1):
            low, high = max(-i, delta - (tau - i)), min(i, delta + (tau - i))
            found += [(delta, i, shift) for shift in range(low, high + 1)]
    return sorted(found, key=lambda x: (x[0] != 0 or x[2] != 0, x))


def with_segments(df: DataFrame, tau: int = TAU) -> DataFrame:
    """For each length probed: the size of its segments (``q``) and how many, the last ones, are longer by one (``r``)."""
    cols = {}
    for delta in range(tau + 1):
        rest = F.pmod(F.col("len") - delta, F.lit(tau + 1))
        cols[f"r{delta}"], cols[f"q{delta}"] = rest, ((F.col("len") - delta - rest) / (tau + 1)).cast("int")
    return df.withColumns(cols)


def segment_keys(tau: int = TAU) -> list[Column]:
    """One hash for each probe of ``line``, null where the substring would leave it; needs ``with_segments``."""
    keys = []
    for delta, i, shift in probes(tau):
        q, longer = F.col(f"q{delta}"), F.lit(i) - (F.lit(tau + 1) - F.col(f"r{delta}"))  # this segment's number among the longer ones
        start, size = q * i + F.greatest(F.lit(0), longer) + shift, q + (longer >= 0).cast("int")
        inside = (start >= 0) & (start + size <= F.col("len")) & (q > 0)
        keys.append(F.when(inside, F.xxhash64(F.col("len") - delta, F.lit(i), F.substring("line", start + 1, size))))
    return keys


def letter_counts(line: Column) -> Column:
    """How often each of ten letters occurs, modulo 64 in six bits each."""
    each = [(F.octet_length(line) - F.octet_length(F.replace(line, F.lit(c), F.lit("")))).bitwiseAND(F.lit(63)).cast("long") for c in LETTERS]
    return reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(c, 6 * j) for j, c in enumerate(each)])


def letter_distance(a: Column, b: Column) -> Column:
    """Differences of the counts, around the circle of 64: never more than the counts really differ by."""
    apart = lambda j: (F.shiftright(a, 6 * j) - F.shiftright(b, 6 * j)).bitwiseAND(F.lit(63))
    return reduce(lambda x, y: x + y, [F.least(apart(j), F.lit(64) - apart(j)) for j in range(len(LETTERS))])


def _shared_start(a: Column, b: Column) -> Column:
    """Length of the longest common prefix, by halving steps."""
    most = F.least(F.length(a), F.length(b))
    steps = F.array(*[F.lit(1 << j) for j in range(24, -1, -1)])
    fits = lambda n, w: (n + w <= most) & (F.substring(a, n + 1, w) == F.substring(b, n + 1, w))
    return F.aggregate(steps, F.lit(0), lambda n, w: F.when(fits(n, w), n + w).otherwise(n))


def _once(value: Column, use) -> Column:
    """``use(value)`` with value computed once: a lambda's variable is, a repeated expression is not."""
    return F.element_at(F.transform(F.array(value), use), 1)


def within(a: Column, b: Column, tau: int = TAU) -> Column:
    """Whether two strings, ``a`` at least as long as ``b``, are within ``tau`` edits: what they share at both ends is cut off first."""
    pair = lambda x, y: F.struct(x.alias("a"), y.alias("b"))
    tails = lambda z, n: pair(F.reverse(F.substring(z["a"], n + 1, F.length(z["a"]))), F.reverse(F.substring(z["b"], n + 1, F.length(z["b"]))))
    cut = lambda z: _once(_shared_start(z["a"], z["b"]), lambda n: tails(z, n))
    return _once(pair(a, b), lambda z: _once(cut(z), lambda y: _once(cut(y), lambda x: banded_distance(x["a"], x["b"], tau) <= tau)))


def banded_distance(a: Column, b: Column, tau: int = TAU) -> Column:
    """Edit distance of two strings, ``a`` at least as long as ``b``; any value above ``tau`` only says so.

    Bit ``top`` of the state belongs to cell (i + tau) of pattern ``a`` when text character i of ``b`` is read,
    so the band slides down the diagonal by one bit a step. Past the pattern's end the score is read
    along its last row, whose bit then moves down. Once the score cannot come back, steps do nothing.
    """
    top = 2 * tau + _PAD
    full = (1 << (top + 1)) - 1

    def walk(z: Column) -> Column:
        p, t, m, n = z["p"], z["t"], z["m"], z["n"]  # p has tau empty cells at either end

        def step(s: Column, i: Column) -> Column:
            match = reduce(lambda x, y: x + y, [F.when(F.element_at(p, i + 1 + j) == F.element_at(t, i + 1), F.lit(1 << (top - 2 * tau + j))).otherwise(F.lit(0)) for j in range(2 * tau + 1)])
            return F.when(s["score"] > 2 * tau, s).otherwise(_once(match, lambda x: _once(column(s, x), lambda c: moved(s, c, i))))

        inv = lambda x: x.bitwiseXOR(F.lit(full))

        def column(s: Column, match: Column) -> Column:
            vp, vn = s["vp"], s["vn"]
            d0 = (match.bitwiseAND(vp) + vp).bitwiseXOR(vp).bitwiseOR(match).bitwiseOR(vn).bitwiseAND(F.lit(full))
            return _once(d0, lambda d: F.struct(d.alias("d0"), vn.bitwiseOR(inv(d.bitwiseOR(vp))).alias("hp"), d.bitwiseAND(vp).alias("hn")))

        def moved(s: Column, c: Column, i: Column) -> Column:
            d0, hp, hn = c["d0"], c["hp"], c["hn"]
            x = F.shiftright(d0, 1)
            last = F.greatest(F.least(m - 1 - i + (top - tau), F.lit(top)), F.lit(0))  # bit of the pattern's last cell
            here = lambda v: F.call_function("shiftright", v, last).bitwiseAND(F.lit(1))
            score = s["score"] + F.when(i + tau < m, F.lit(1) - F.shiftright(d0, top).bitwiseAND(F.lit(1))).otherwise(here(hp) - here(hn))
            return F.struct(hn.bitwiseOR(inv(x.bitwiseOR(hp))).alias("vp"), x.bitwiseAND(hp).alias("vn"), score.cast("int").alias("score"))

        start = F.struct(F.lit(full & ~((1 << (top - tau)) - 1)).alias("vp"), F.lit(0).alias("vn"), F.least(m, F.lit(tau)).alias("score"))
        walked = F.aggregate(F.sequence(F.lit(0), n - 1), start, step, lambda s: s["score"])
        return F.when(m - n > tau, F.lit(tau + 1)).when(n == 0, m).otherwise(walked)

    edge = F.array_repeat(F.lit(""), tau)
    return _once(F.struct(F.concat(edge, F.split(a, ""), edge).alias("p"), F.split(b, "").alias("t"), F.length(a).alias("m"), F.length(b).alias("n")), walk)


def _own_rows(docs: DataFrame) -> DataFrame:
    """``docs`` with ``__row``: 0 for rows whose id no other row has; the others, and those without an id, are numbered from 1."""
    twice = Kept(docs.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").select("doc_id"), "twice").df
    n_twice = twice.count()
    if not n_twice and docs.where("doc_id IS NULL").isEmpty():
        return docs.withColumn("__row", F.lit(0).cast("long"))
    again = F.broadcast(twice) if n_twice <= BROADCAST_ROWS else twice
    shared = docs.where("doc_id IS NULL").unionByName(docs.join(again, "doc_id", "left_semi").select(*docs.columns))
    rows = Kept(shared.withColumn("__row", F.monotonically_increasing_id()), "rows").df  # a split's number above 33 bits of the row's
    split = F.shiftright("__row", 33)
    sizes = rows.groupBy(split.alias("__split")).agg(F.count(F.lit(1)).alias("n")).orderBy("__split").collect()
    before, total = {}, 0
    for r in sizes:
        before[r["__split"]] = total
        total += r.n
    if total > MOST_NUMBERED:
        raise OverflowError(f"{total} rows share an id or have none; {MOST_NUMBERED} can be numbered")
    first = docs.sparkSession.createDataFrame(list(before.items()), "__split long, __first long")
    numbered = rows.withColumn("__split", split).join(F.broadcast(first), "__split").withColumn("__row", F.col("__first") + F.col("__row").bitwiseAND(F.lit((1 << 33) - 1)) + 1)
    own = docs.where("doc_id IS NOT NULL").join(again, "doc_id", "left_anti").withColumn("__row", F.lit(0).cast("long"))
    return own.select(*docs.columns, "__row").unionByName(numbered.select(*docs.columns, "__row"))


def _occurrences(docs: DataFrame, least: int = EXACT_CHARS) -> DataFrame:
    lines = F.split(F.coalesce("text", F.lit("")), "\n")
    return docs.select("doc_id", "__row", F.posexplode(lines).alias("line_no", "line")).where((F.length("line") >= least) & (F.trim("line") != ""))


def _place() -> Column:
    """(doc_id, row, line number) as one number that sorts alike: 63 bits below the id, 31 of them the line's."""
    low = F.shiftleft(F.col("__row"), 31) + F.col("line_no")
    return F.coalesce(F.col("doc_id").cast("decimal(20,0)"), F.lit(Decimal(-(2**63) - 1))) * F.lit(Decimal(2**63)) + low.cast("decimal(19,0)")


def _hashes() -> list[Column]:
    return [F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(77), "line").alias("h2")]


def distinct_lines(docs: DataFrame, tau: int = TAU, least: int = EXACT_CHARS, most: int | None = None) -> Kept:
    """One row a distinct line: first place, occurrences, hashes, and what the join needs of its text.

    Only hashes and keys are brought together, not the texts; lines are told apart by 128 bits.
    """
    keys = [c.alias(f"k{j}") for j, c in enumerate(segment_keys(tau))]
    found = _occurrences(docs, least)
    occ = with_segments((found.where(F.length("line") <= most) if most else found).withColumn("len", F.length("line")), tau)
    # The empty lambda keeps this step out of whole-stage code, whose one method would be too long to be compiled.
    occ = occ.select(*_hashes(), _place().alias("place"), _once(F.col("len"), lambda n: n).alias("len"), letter_counts(F.col("line")).alias("letters"), *keys)
    same = [F.max(c).alias(c) for c in ("len", "letters", *[f"k{j}" for j in range(len(keys))])]  # equal for all occurrences
    per = occ.groupBy("h1", "h2").agg(F.min("place").alias("place"), F.count(F.lit(1)).alias("n"), *same)
    return Kept(per.select(F.monotonically_increasing_id().alias("lid"), "h1", "h2", "place", "n", "len", "letters", F.array(*[f"k{j}" for j in range(len(keys))]).alias("keys")), "lines")


def near_pairs(docs: DataFrame, lines: DataFrame, tau: int = TAU, least: int = NEAR_CHARS, below: int | None = None) -> DataFrame:
    """``(a, b)``: ids of distinct lines within ``tau`` edits, ``a`` the longer; ``below`` bounds the length of ``b``."""
    spread = lines.where(F.col("len") >= least).select("lid", "len", "letters", F.posexplode("keys").alias("p", "key")).where("key IS NOT NULL")
    index = spread.where((F.col("p") <= tau) & (F.col("len") < below if below else F.lit(True))).select("key", F.col("lid").alias("b"), F.col("letters").alias("cb"))
    # The key holds the shorter length, so only probes of a line's own length could meet a pair twice.
    same = F.col("p").isin([p for p, (delta, _, _) in enumerate(probes(tau)) if delta == 0])
    probe = spread.select("key", F.when(same, -F.col("lid") - 1).otherwise(F.col("lid")).alias("a"), F.col("letters").alias("ca"))
    ordered = (F.col("a") >= 0) | (-F.col("a") - 1 < F.col("b"))
    alike = letter_distance(F.col("ca"), F.col("cb")) <= 2 * tau
    met = probe.join(index, (probe["key"] == index["key"]) & ordered & alike)
    found = Kept(met.select(F.when(F.col("a") < 0, -F.col("a") - 1).otherwise(F.col("a")).alias("a"), "b").distinct(), "pairs")

    # The texts of lines in pairs come from one more scan; few lines are looked up by broadcast, many by a shuffle.
    wanted = found.df.select(F.col("a").alias("lid")).union(found.df.select("b")).distinct()
    wanted = Kept(lines.join(wanted, "lid", "left_semi").select("lid", "h1", "h2"), "wanted")
    few = wanted.df.count() <= BROADCAST_ROWS
    occ = _occurrences(docs).where(F.length("line") >= least).select("line", *_hashes())
    texts = occ.join(F.broadcast(wanted.df) if few else wanted.df, ["h1", "h2"]).groupBy("lid", "line").agg(F.count(F.lit(1)).alias("c")).select("lid", "line")
    texts = Kept(texts, "texts").df
    one, two = texts.select(F.col("lid").alias("a"), F.col("line").alias("ta")), texts.select(F.col("lid").alias("b"), F.col("line").alias("tb"))
    return found.df.join(one, "a").join(two, "b").where(within(F.col("ta"), F.col("tb"), tau)).select("a", "b")


def _later(pairs: DataFrame, lines: DataFrame) -> DataFrame:
    """``lid`` of the later line of each pair."""
    places = lines.select("lid", "place")
    both = pairs.join(places.withColumnRenamed("place", "pa").withColumnRenamed("lid", "a"), "a").join(places.withColumnRenamed("place", "pb").withColumnRenamed("lid", "b"), "b")
    return Kept(both.select(F.when(F.col("pa") > F.col("pb"), F.col("a")).otherwise(F.col("b")).alias("lid")).distinct(), "later").df


def judged_lines(docs: DataFrame, tau: int = TAU, short: bool = False) -> DataFrame:
    """``(h1, h2, place, near)`` of lines that occur again or lie near an earlier line."""
    lines = distinct_lines(docs, tau, 1 if short else EXACT_CHARS)
    later = _later(near_pairs(docs, lines.df, tau), lines.df)
    if short:
        brief = distinct_lines(docs, SHORT_TAU, EXACT_CHARS, NEAR_CHARS - 1 + SHORT_TAU).df
        nearby = _later(near_pairs(docs, brief, SHORT_TAU, EXACT_CHARS, NEAR_CHARS), brief)
        hashes = brief.join(nearby, "lid", "left_semi").select("h1", "h2")
        later = later.union(lines.df.join(hashes, ["h1", "h2"], "left_semi").select("lid")).distinct()
    flagged = lines.df.select("lid", "h1", "h2", "place", "n").join(later.withColumn("near", F.lit(True)), "lid", "left").where("n > 1 OR near")
    return Kept(flagged.select("h1", "h2", "place", F.coalesce("near", F.lit(False)).alias("near")), "judged").df


def line_report(docs: DataFrame, tau: int = TAU, short: bool = False) -> DataFrame:
    """``(doc_id, n_lines, exact_repeats, near_repeats, kept_chars)``: kept_chars without the newlines."""
    docs = _own_rows(docs.select("doc_id", "text"))
    judged = judged_lines(docs, tau, short)
    occ = _occurrences(docs, 1 if short else EXACT_CHARS).select("doc_id", "__row", _place().alias("at"), F.length("line").alias("len"), *_hashes())
    hit = occ.join(judged, ["h1", "h2"]).where(F.col("near") | (F.col("at") != F.col("place")))
    per = hit.groupBy("doc_id", "__row").agg(F.sum((~F.col("near")).cast("long")).alias("exact"), F.sum(F.col("near").cast("long")).alias("nearly"), F.sum("len").alias("chars"))
    text = F.coalesce("text", F.lit(""))
    n_lines = F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1
    whole = docs.select("doc_id", "__row", n_lines.cast("long").alias("n_lines"), (F.length(text) - n_lines + 1).cast("long").alias("chars_in"))
    zero = F.lit(0).cast("long")
    return whole.join(per.withColumnsRenamed({"doc_id": "d", "__row": "r"}), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("__row") == F.col("r")), "left").select(
        "doc_id", "n_lines", F.coalesce("exact", zero).alias("exact_repeats"), F.coalesce("nearly", zero).alias("near_repeats"), (F.col("chars_in") - F.coalesce("chars", zero)).alias("kept_chars")
    )


def dedup_lines(docs: DataFrame, tau: int = TAU, short: bool = False) -> DataFrame:
    """All columns of ``docs``, ``text`` without dropped lines (and ``n_chars``, if there, as its new length).

    Documents that lose all their lines go: all they say is said elsewhere. Others keep line order.
    """
    given, docs = docs, _own_rows(docs)
    judged = judged_lines(docs, tau, short)
    occ = _occurrences(docs, 1 if short else EXACT_CHARS).select("doc_id", "__row", "line_no", _place().alias("at"), *_hashes())
    hit = occ.join(judged, ["h1", "h2"]).where(F.col("near") | (F.col("at") != F.col("place")))
    dropped = hit.groupBy("doc_id", "__row").agg(F.collect_set("line_no").alias("__dropped")).withColumnsRenamed({"doc_id": "__doc", "__row": "__at"})
    joined = docs.join(Kept(dropped, "dropped").df, F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("__row") == F.col("__at")), "left")
    kept = F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains("__dropped", i))
    text = F.when(F.col("__dropped").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))
    out = joined.withColumn("text", text).where(F.col("__dropped").isNull() | (F.trim(F.translate("text", "\n\r\t", "   ")) != ""))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("__dropped").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out.select(*given.columns)

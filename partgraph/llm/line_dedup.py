"""Line dedup by a segment-partition edit join, in DataFrame functions alone.

A line leaves when an earlier line (by doc_id, then a hash of the document, then place) equals it or is near it: within
one edit for each MIN_CHARS / THRESHOLD code points of the shorter line, THRESHOLD at most. All lines that hold a word
take part; lines too short for an edit leave as exact copies. Two lines within t edits share one of t + 1 segments: every
line indexes its segments by (length class, segment, content) and probes the substrings that can match one in its class.
Signatures that only one line has go first; hot ones are split. A semi join keeps the lines that meet an earlier near one:
it tests length, letters and pairs of them held an odd number of times, and then a banded bit-parallel edit distance: the band of a column
is one integer, moved along the diagonal. It makes no rows for pairs, so a group of near copies costs a row for each line.

Texts are shuffled by document for the lines that share a signature and for the final cut, and with these signatures.

Cases: a null or empty text has no lines and stays as it is; blank lines stay; rows equal in doc_id and text are one
document and get the same result; a null doc_id comes before all others; other columns are kept by ``dedup_lines``,
whatever their names, but ``n_lines`` and ``n_removed`` give way to its counts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import forget, spill

THRESHOLD = 2
#: Code points from which a line may differ by THRESHOLD edits.
MIN_CHARS = 30
#: Lengths of a class differ by this factor at most.
GROWTH = 1.25
#: Entries of a signature that one task pairs with all others of that signature.
SPLIT = 1024


def _places(n: Column, size: Column, t: int) -> Column:
    """Where segments and what may equal them start: (at, code) structs; the lowest bit of ``code`` marks a line's own
    segments, which it indexes, the others are probes only.

    Lines of a length class have t + 1 segments of one size. Two lines within t edits share a segment i that has at most i
    edits to its left and t - i to its right: it is looked for near its place from the start, or, in the second half, from
    the end.
    """
    out = []
    for i in range(t + 1):
        reach = min(i, t - i)
        for shift in range(-reach, reach + 1):
            at = (size * i if 2 * i <= t else n - size * (t + 1 - i)) + shift
            out.append(F.struct(at.cast("int").alias("at"), F.lit((i * 8 + t) * 2 + int(shift == 0)).alias("code")))
    return F.array(*out)


def _size(c: Column, low: int, t: int) -> Column:
    return F.floor((F.floor(low * F.pow(F.lit(GROWTH), c)) - t - 1) / (t + 1)).cast("int")


def _class(n: Column, low: int) -> Column:
    """Length class: lines of like length; their segments are cut for the shortest of them."""
    return F.floor(F.log(n / low) / F.log(F.lit(GROWTH))).cast("int")


def _trimmed(a: Column, b: Column, most: int = 20) -> Column:
    """Code points that two strings share at their start, found by halving steps (up to 2 ** most)."""
    short = F.least(F.char_length(a), F.char_length(b))
    steps = F.array(*[F.lit(1 << e) for e in range(most, -1, -1)])
    grow = lambda p, s: F.when((p + s <= short) & (F.substring(a, p + 1, s) == F.substring(b, p + 1, s)), p + s).otherwise(p)
    return F.aggregate(steps, F.lit(0), grow)


def _let(value: Column, use) -> Column:
    """``use`` of a value that is computed once."""
    return F.transform(F.array(value), use)[0]


def edits_within(long: Column, short: Column, t: int) -> Column:
    """Edit distance of two arrays of characters (the first not the shorter one), or a number above ``t``.

    Column j of the table holds rows j - t .. j + t in 2t + 1 bits: ``vp`` and ``vn`` mark vertical steps of +1 and -1.
    The distance is read off the diagonal that ends in the last cell; it rises where that diagonal's step is not free.
    """
    full = (1 << (2 * t + 1)) - 1
    big = lambda x: F.lit(x).cast("bigint")

    def run(gap: Column) -> Column:
        def same(j: Column, c: Column) -> Column:
            marks = [F.when(F.coalesce(F.get(long, j + (b - t)) == c, F.lit(False)), big(1 << b)).otherwise(big(0)) for b in range(2 * t + 1)]
            return sum(marks[1:], marks[0])

        def moved(s: Column, d: Column, hp: Column) -> Column:
            return F.struct(
                d.bitwiseAND(s["vp"]).bitwiseOR(big(full).bitwiseXOR(F.shiftright(d, 1).bitwiseOR(hp))).alias("vp"),
                F.shiftright(d, 1).bitwiseAND(hp).alias("vn"),
                (s["miss"] + 1 - F.getbit(d, F.lit(t) + gap)).cast("int").alias("miss"),
            )

        def step(s: Column, j: Column) -> Column:
            free = lambda x: ((x.bitwiseAND(s["vp"]) + s["vp"]).bitwiseXOR(s["vp"])).bitwiseOR(x).bitwiseOR(s["vn"]).bitwiseAND(big(full))
            rise = lambda d: s["vn"].bitwiseOR(big(full).bitwiseXOR(d.bitwiseOR(s["vp"])))
            return _let(F.get(short, j), lambda c: _let(same(j, c), lambda x: _let(free(x), lambda d: _let(rise(d), lambda hp: moved(s, d, hp)))))

        start = F.struct(big(full ^ ((1 << t) - 1)).alias("vp"), big(0).alias("vn"), gap.cast("int").alias("miss"))
        places = F.when(F.size(short) > 0, F.sequence(F.lit(0), F.size(short) - 1)).otherwise(F.array().cast("array<int>"))
        return F.when(gap > t, F.lit(t + 1)).otherwise(F.aggregate(places, start, lambda s, j: F.when(s["miss"] > t, s).otherwise(step(s, j)), lambda s: s["miss"]))

    return _let(F.size(long) - F.size(short), run)


def near(a: Column, b: Column, t: int = THRESHOLD, min_chars: int = MIN_CHARS) -> Column:
    """Whether two lines are within the edits that the shorter one allows; shared starts and ends are cut off first."""
    chars = lambda s: F.when(F.char_length(s) > 0, F.split(s, "")).otherwise(F.array().cast("array<string>"))
    rest = lambda s, cut: F.substring(s, cut + 1, F.char_length(s))
    pair = lambda x, y: F.struct(x.alias("x"), y.alias("y"))

    def both(p: Column) -> Column:
        allowed = F.least(F.lit(t), F.floor(F.char_length(p["y"]) * t / min_chars).cast("int"))
        turned = lambda head: pair(F.reverse(rest(p["x"], head)), F.reverse(rest(p["y"], head)))
        middle = lambda q: _let(_trimmed(q["x"], q["y"]), lambda cut: _let(pair(chars(rest(q["x"], cut)), chars(rest(q["y"], cut))), lambda w: edits_within(w["x"], w["y"], t)))
        return _let(_trimmed(p["x"], p["y"]), lambda head: _let(turned(head), middle)) <= allowed

    longer = F.char_length(a) >= F.char_length(b)
    return _let(F.when(longer, pair(a, b)).otherwise(pair(b, a)), both)


def _keyed(docs: DataFrame) -> DataFrame:
    """(k, c, doc_id, text): k and c name a document by its id and text."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.xxhash64("doc_id", text).alias("k"), F.crc32(text).alias("c"), "doc_id", text.alias("text"))


def lines_of(keyed: DataFrame) -> DataFrame:
    """(k, c, doc_id, pos, line, lh, lc): the lines that take part; lh and lc name a line."""
    rows = keyed.select("k", "c", "doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    return rows.where(F.ltrim("line", F.lit(" \t\n\v\f\r")) != "").select("*", F.xxhash64("line").alias("lh"), F.crc32("line").alias("lc"))


def shared_signatures(lines: DataFrame, t: int, min_chars: int) -> DataFrame:
    """(sign, lh, mark, splits), spilled: the signatures that several lines have. ``mark`` holds the line's length and, in
    its lowest bit, whether the line indexes the signature; ``splits`` is in how many parts those are joined."""
    wide = lines.select("lh", "line", F.char_length("line").alias("n")).where(F.col("n") >= -(-min_chars // t))
    wide = wide.select("lh", "n", F.encode("line", "UTF-32").alias("wide"))
    lists = []
    for k in range(1, t + 1):
        low, high = -(-k * min_chars // t), -(-(k + 1) * min_chars // t) - 1 + k
        fits = (F.col("n") >= low) & (F.lit(k == t) | (F.col("n") <= high))
        # a line joins the class of lines that are longer by k edits, too, so that no pair is parted by a border
        own, next_ = _class(F.col("n"), low), _class(F.col("n") + k, low)
        for c, ok in ((own, F.lit(True)), (next_, next_ != own)):
            lists.append(F.when(fits & ok, F.struct(c.alias("c"), F.lit(k).alias("k"), _size(c, low, k).alias("size"))))
    rows = wide.select("lh", "n", "wide", F.explode(F.array(*lists)).alias("x")).where("x is not null").select("lh", "n", "wide", "x.*")
    places = _places(F.col("n"), F.col("size"), t)
    for k in range(1, t):
        places = F.when(F.col("k") == k, _places(F.col("n"), F.col("size"), k)).otherwise(places)
    rows = rows.select("lh", "n", "wide", "c", "size", F.explode(places).alias("p")).select("*", "p.at", "p.code")
    rows = rows.where((F.col("at") >= 0) & (F.col("at") + F.col("size") <= F.col("n")))
    sign = F.xxhash64(F.substring("wide", F.col("at") * 4 + 1, F.col("size") * 4), F.col("c") * 64 + F.shiftright("code", 1))
    rows = rows.select(sign.alias("sign"), "lh", (F.col("n") * 2 + F.col("code").bitwiseAND(F.lit(1))).alias("mark"))
    dealt = rows.repartition("sign")
    own = F.col("mark").bitwiseAND(F.lit(1))
    met = dealt.groupBy("sign").agg(F.min("lh").alias("low"), F.max("lh").alias("high"), F.max(own).alias("any_own"), F.count("*").alias("met"))
    met = met.where("low <> high and any_own = 1").select("sign", F.ceil(F.col("met") / SPLIT).cast("int").alias("splits"))
    return spill(dealt.join(met.hint("shuffle_hash"), "sign"))


def _odd_letters(line: Column) -> Column:
    """64 bits: which characters (by code modulo 64) a line holds an odd number of times; an edit changes two at most."""
    flip = lambda x, c: x.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(F.ascii(c), F.lit(64))))
    return F.aggregate(F.split(line, ""), F.lit(0).cast("bigint"), flip)


def _odd_pairs(line: Column, words: int = 2) -> list[Column]:
    """``words`` times 64 bits: which hashes of two neighbouring characters (the last one and nothing, too) a line holds an
    odd number of times; a replaced character changes four at most, one put in or taken out three."""
    codes = F.transform(F.split(line, ""), lambda c: F.ascii(c))
    pairs = lambda x: F.zip_with(x, F.slice(x, 2, F.greatest(F.size(x), F.lit(1))), lambda a, b: F.pmod(a * 73 + F.coalesce(b, F.lit(0)) * 19, F.lit(64 * words)))
    flip = lambda x, h: x.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(h, F.lit(64))))
    of_word = lambda w: lambda v: F.shiftright(v, 6) == w
    held = lambda h: F.array(*[F.aggregate(F.filter(h, of_word(w)), F.lit(0).cast("bigint"), flip) for w in range(words)])
    masks = _let(codes, lambda c: _let(pairs(c), held))
    return [F.get(masks, w).alias(f"pairs{w}") for w in range(words)]


def _meets(rows: DataFrame, index: Column, probe: Column, keys: list[str], t: int, min_chars: int) -> DataFrame:
    """(lh, lc) of ``probe`` rows that have an earlier near line among the ``index`` rows of their ``keys``.

    The whole comparison stands in a left semi join: it ends at a line's first match and makes no row for a pair.
    """
    took = ("mark", "odd", "pairs0", "pairs1", "first", "line")
    # as many tasks as a shuffle has: what is joined is small, comparing it is not
    deal = lambda df, p: df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *[f"{p}_{c}" for c in keys])
    x = rows.where(index & (F.col("mark").bitwiseAND(F.lit(1)) == 1)).select(*[F.col(c).alias(f"x_{c}") for c in (*keys, *took)])
    y = rows.where(probe).select("lh", "lc", *[F.col(c).alias(f"y_{c}") for c in (*keys, *took)])
    if "salt" in keys:
        y = y.withColumn("y_salt", F.explode(F.sequence(F.lit(1), F.col("y_salt"))))
    meets = F.col("x_first") < F.col("y_first")
    for c in keys:
        meets &= F.col(f"x_{c}") == F.col(f"y_{c}")
    n, m = F.shiftright("x_mark", 1), F.shiftright("y_mark", 1)
    allowed = F.least(F.lit(t), F.expr(f"least(shiftright(x_mark, 1), shiftright(y_mark, 1)) * {t} div {min_chars}").cast("int"))
    flips = lambda c: F.bit_count(F.col(f"x_{c}").bitwiseXOR(F.col(f"y_{c}")))
    meets &= (F.abs(n - m) <= allowed) & (flips("odd") <= 2 * allowed - F.abs(n - m)) & (flips("pairs0") + flips("pairs1") <= 4 * allowed - F.abs(n - m))
    return deal(y, "y").join(deal(x, "x"), meets & near(F.col("x_line"), F.col("y_line"), t, min_chars), "left_semi").select("lh", "lc").distinct()


def later_lines(shared: DataFrame, texts: DataFrame, t: int, min_chars: int) -> DataFrame:
    """(lh, lc), spilled: the lines near an earlier one that shares a signature.

    Either line of a near pair finds the other one, so the earlier line is indexed and the later one probes. First every
    line probes one part of each signature's index; in a group of near copies most lines leave by that. Lines that stay
    and have a signature of several parts then probe the other parts.
    """
    part = F.pmod(F.xxhash64("lh"), F.col("splits")).cast("int")
    rows = shared.join(texts, "lh")
    found = spill(_meets(rows, part == 0, F.lit(True), ["sign"], t, min_chars))
    hot = shared.where("splits > 1")
    if hot.isEmpty():
        return found
    names = hot.join(texts, "lh").join(found.withColumn("settled", F.lit(True)), ["lh", "lc"], "left")
    # an index row's salt is its part; a probe's is the last part, and it probes all parts from 1 on
    ends = names.select("*", part.alias("part"), F.explode(F.array(F.lit(False), F.lit(True))).alias("probe"))
    ends = ends.where((F.col("probe") & F.col("settled").isNull()) | (~F.col("probe") & (F.col("part") > 0)))
    ends = ends.withColumn("salt", F.when(F.col("probe"), F.col("splits") - 1).otherwise(F.col("part")))
    more = _meets(ends, ~F.col("probe"), F.col("probe"), ["sign", "salt"], t, min_chars)
    return spill(found.unionByName(more), found)


def _with_text(keyed: DataFrame, rows: DataFrame, *columns: str, how: str = "inner") -> DataFrame:
    """``keyed`` with ``columns`` of the row that has its key; equal exchanges of texts are reused."""
    right = rows.select(F.col("k").alias("__k"), F.col("c").alias("__c"), *columns)
    return keyed.join(right, (keyed["k"] == right["__k"]) & (keyed["c"] == right["__c"]), how).drop("__k", "__c")


def similar_lines(keyed: DataFrame, places: DataFrame, t: int = THRESHOLD, min_chars: int = MIN_CHARS) -> DataFrame:
    """(lh, lc), spilled: the distinct lines that are near an earlier one.

    ``places`` holds (lh, lc, first): where each distinct line stands first.
    """
    shared = shared_signatures(lines_of(keyed), t, min_chars)
    wanted = shared.select("lh").distinct()
    at = places.join(wanted, "lh", "left_semi").select("lh", "lc", "first", "first.k", "first.c")
    held = at.groupBy("k", "c").agg(F.collect_list(F.struct("lh", "lc", "first")).alias("wanted"))
    cut = _with_text(keyed, held, "wanted").dropDuplicates(["k", "c"]).select("wanted", F.split("text", "\n", -1).alias("lines"))
    texts = cut.select(F.explode(F.transform("wanted", lambda w: F.struct(w["lh"].alias("lh"), w["lc"].alias("lc"), w["first"].alias("first"), F.get("lines", w["first"]["pos"]).alias("line")))).alias("x")).select("x.*")
    texts = spill(texts.select("*", _odd_letters(F.col("line")).alias("odd"), *_odd_pairs(F.col("line"))))
    later = later_lines(shared, texts, t, min_chars)
    forget(shared, texts)
    return later


def removed_lines(keyed: DataFrame, t: int = THRESHOLD, min_chars: int = MIN_CHARS) -> DataFrame:
    """(k, c, removed): places of the lines that leave, for the documents that lose any."""
    occurrences = spill(lines_of(keyed).select("lh", "lc", "doc_id", "k", "c", "pos"))
    place = F.struct("doc_id", "k", "c", "pos")
    lines = spill(occurrences.groupBy("lh", "lc").agg(F.min(place).alias("first"), F.max(place).alias("last")))
    later = similar_lines(keyed, lines.select("lh", "lc", "first"), t, min_chars).withColumn("gone", F.lit(True))
    decided = lines.join(later, ["lh", "lc"], "left").where(F.col("gone") | (F.col("first") != F.col("last"))).select("lh", "lc", "first", F.coalesce("gone", F.lit(False)).alias("gone"))
    leaving = occurrences.join(decided, ["lh", "lc"]).where(F.col("gone") | (place != F.col("first")))
    removed = spill(leaving.groupBy("k", "c").agg(F.collect_set("pos").alias("removed")), lines)
    forget(occurrences)
    return removed


def dedup_lines(docs: DataFrame, t: int = THRESHOLD, min_chars: int = MIN_CHARS) -> DataFrame:
    """``docs`` with the leaving lines cut from ``text``, and n_lines, n_removed beside all columns."""
    names = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.xxhash64("doc_id", text).alias("k"), F.crc32(text).alias("c"), F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"))
    met = _with_text(rows, removed_lines(_keyed(docs), t, min_chars), "removed", how="left")
    text = F.col("row.text")
    kept = F.array_join(F.filter(F.split(text, "\n", -1), lambda x, i: ~F.array_contains("removed", i)), "\n")
    return met.select(
        *[(F.when(F.col("removed").isNull(), text).otherwise(kept) if c == "text" else F.col(f"row.`{c}`")).alias(c) for c in names],
        F.when(F.coalesce(text, F.lit("")) == "", 0).otherwise(F.size(F.split(text, "\n", -1))).cast("bigint").alias("n_lines"),
        F.coalesce(F.size("removed"), F.lit(0)).cast("bigint").alias("n_removed"),
    )


def op8_segment_edit_lines(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def filter_lines(docs: DataFrame) -> DataFrame:
    """The documents with their kept lines, same columns (but n_lines and n_removed, if there, hold the counts)."""
    return dedup_lines(docs).select(*[F.col(f"`{c}`") for c in docs.columns])

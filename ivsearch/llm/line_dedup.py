"""Line dedup: exact copies by hash, near copies by a segment-partition edit join with bit-parallel verification."""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BLANKS, hidden, shown, small, stage, table, width

#: Within which a line and an earlier one count as near copies, and from which length on.
EDITS, MIN_CHARS = 2, 32


def bounded_distance(df: DataFrame, a: str, b: str, k: int) -> DataFrame:
    """df with edits: the edit distance of columns a and b, b at most k shorter than a and not longer; exact up to k, above k otherwise.

    A band of 2k+1 rows around the diagonal moves down one row with each character of b. Which rows of the band match the
    character is one bit set, the vertical differences +1 and -1 are two more, and a few integer operations give the
    band's next column. The distance is read along the diagonal that ends in the last cell: it starts at the
    difference of the lengths and grows by one wherever the diagonal step costs one.
    """
    rows = 2 * k + 1
    full = F.lit((1 << rows) - 1).cast("long")
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    # What a lambda holds is computed again for each element, and a filter may be moved below a projection but not below explode().
    chars = F.struct(F.split(a, "").alias("x"), F.filter(F.split(b, ""), lambda c: c != "").alias("y"))
    df = df.withColumn("_c", F.explode(F.array(chars)))
    masks = F.transform("_c.y", lambda c, j: sum((F.when(F.get("_c.x", j - k + i) == c, F.lit(1 << i).cast("long")).otherwise(none) for i in range(rows)), none))
    gap = (F.length(a) - F.length(b)).cast("int")
    start = F.struct(F.lit(((1 << (k + 1)) - 1) << k).cast("long").alias("up"), none.alias("down"), gap.cast("long").alias("d"), (gap + k).alias("row"))

    def step(s: Column, m: Column) -> Column:
        up, down = s["up"], s["down"]
        free = (m.bitwiseAND(up) + up).bitwiseXOR(up).bitwiseOR(m).bitwiseOR(down).bitwiseAND(full)
        right = down.bitwiseOR(F.bitwise_not(free.bitwiseOR(up))).bitwiseAND(full)
        fall = F.shiftright(free, 1)
        paid = one - F.call_function("shiftright", free, s["row"]).bitwiseAND(one)
        return F.struct(free.bitwiseAND(up).bitwiseOR(F.bitwise_not(fall.bitwiseOR(right))).bitwiseAND(full).alias("up"), fall.bitwiseAND(right).alias("down"), (s["d"] + paid).alias("d"), s["row"].alias("row"))

    return df.withColumn("_m", masks).withColumn("edits", F.aggregate("_m", start, step)["d"]).drop("_c", "_m")


#: What a key row is: one of a line's own segments, a probe for lines of equal length, a probe for shorter ones.
OWN, EQUAL, SHORTER = 0, 1, 2


def key_plan(k: int) -> list[tuple[int, int, int, int]]:
    """(kind, g, i, o) of all keys of a line: a line shorter by g is cut in k+1 segments, and segment i of it is sought o places away from its own.

    Such a segment can only be found where i edits before it and k - i after it leave room: at most that far, seen from
    either end. For equal lengths, lines' own segments serve as probes, too, and as each line probes the other, up to two edits need
    no shift to the left: if only the middle segment fits there, of the other line's segments the middle one fits to the right or the last one in place.
    """
    plan = [(OWN, 0, i, 0) for i in range(k + 1)]
    for g in range(k + 1):
        for i in range(k + 1):
            for o in range(max(-i, g - (k - i)), min(i, g + (k - i)) + 1):
                if g or (o > 0 or (o < 0 and k > 2)):
                    plan.append((SHORTER if g else EQUAL, g, i, o))
    return plan


def line_keys(line: str, n: str, k: int) -> list[Column]:
    """Index and probe keys of a line of n characters, in the order of key_plan(): 48 bits of a hash of length, segment number and segment; the last segments are the longer ones."""
    x, size = F.col(line), F.col(n)

    def key(g: int, i: int, o: int) -> Column:
        m = size - g
        short, longer = F.floor(m / (k + 1)).cast("int"), (m % (k + 1)).cast("int")
        at = short * i + F.greatest(F.lit(0), longer + (i - (k + 1))) + (1 + o)
        return F.shiftrightunsigned(F.xxhash64(F.substring(x, at, short + F.when(longer + (i - k) > 0, 1).otherwise(0)), m, F.lit(i)), 16)

    return [key(g, i, o) for _, g, i, o in key_plan(k)]


def signed(lines: DataFrame, x: str) -> DataFrame:
    """lines with s1 and s2, bits of the parity of the counts of characters and of pairs of neighbouring characters of x."""
    step = "(s, c) -> named_struct('p', c, 'a', s.a ^ shiftleft(1L, c & 63), 'b', s.b ^ shiftleft(1L, (s.p * 31 + c) & 63))"
    of = F.expr(f"aggregate(transform(split(`{x}`, ''), c -> ascii(c)), named_struct('p', 0, 'a', 0L, 'b', 0L), {step})")
    # One value in an array that explode() takes apart: the two fields then share one evaluation.
    return lines.withColumn("s", F.explode(F.array(of))).select(*lines.columns, F.col("s.a").alias("s1"), F.col("s.b").alias("s2"))


def may_be_near(x: str, y: str, k: int) -> Column:
    """True for all lines within k edits: an edit takes one character and two pairs at most, and adds as many."""
    far = lambda s: F.bit_count(F.col(f"{x}.{s}").bitwiseXOR(F.col(f"{y}.{s}")))
    return (far("s1") <= 2 * k) & (far("s2") <= 4 * k)


def pieces_fit(a: Column, b: Column, k: int, pieces: int = 16) -> Column:
    """True for all lines within k edits: of so many pieces of b, all but k stand in a at most k places away."""
    n = F.length(b)
    short, longer = F.floor(n / pieces).cast("int"), (n % pieces).cast("int")

    def stands(i: Column) -> Column:
        at, size = short * i + F.greatest(F.lit(0), i - pieces + longer) + 1, short + F.when(i - pieces + longer >= 0, 1).otherwise(0)
        piece = F.substring(b, at, size)
        near = [(at + o >= 1) & (F.substring(a, at + o, size) == piece) for o in sorted(range(-k, k + 1), key=abs)]
        return reduce(or_, near)

    return F.size(F.filter(F.sequence(F.lit(0), F.lit(pieces - 1)), stands)) >= pieces - k


def worded(x: Column) -> Column:
    return F.btrim(x, F.lit(BLANKS)) != ""


def owners(docs: DataFrame, k: int, min_chars: int) -> DataFrame:
    """For each distinct line with a word, the place (d, r, p) of its first occurrence by id, then row, then position, and its keys (null if short). Lines are compared by two 64-bit hashes."""
    lines = docs.select("d", "r", F.posexplode(F.split("t", "\n")).alias("p", "x")).where(worded(F.col("x"))).withColumn("n", F.length("x"))
    keyed = lines.select("d", "r", "p", F.xxhash64("x").alias("a"), F.xxhash64(F.lit(7), "x").alias("b"), F.when(F.col("n") >= min_chars, F.array(*line_keys("x", "n", k))).alias("keys"))
    return keyed.groupBy("a", "b").agg(F.min(F.struct("d", "r", "p", "keys")).alias("o")).select("o.*")


def texts(docs: DataFrame, places: DataFrame) -> DataFrame:
    """(d, r, p, x): the lines at places (d, r, p)."""
    at = stage(places.groupBy("d", "r").agg(F.collect_list("p").alias("ps")), "places")  # at most the lines of one document
    docs_, lines = at.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.size("ps")), F.lit(0))).first()
    few = docs_ <= 200_000 and lines <= 1_000_000  # 32 bytes a document and 4 a line, so under 11 MB
    split = docs.join(F.broadcast(at) if few else at, ["d", "r"]).select("d", "r", "ps", F.split("t", "\n").alias("ls"))
    return split.select("d", "r", F.posexplode("ls").alias("p", "x"), "ps").where("array_contains(ps, p)").select("d", "r", "p", "x")


def near_copies(docs: DataFrame, first: DataFrame, k: int) -> DataFrame:
    """Places (d, r, p) of those first lines that lie within k edits of another first line before them (by id, then row, then position).

    Each line is probed against equally long or shorter ones only. Counts by key, aggregated in each task first, tell which keys can
    give a pair at all; only lines with such a key are fetched, once, and get the parity bits that the join on keys compares
    before it makes a row. What it makes is verified. Pairs that share a key but not the bits cost a comparison each, and no row.
    """
    kinds = F.array(*[F.lit(kind) for kind, *_ in key_plan(k)])
    rows = first.where("keys is not null").select("d", "r", "p", F.explode(F.arrays_zip(F.col("keys").alias("key"), kinds.alias("kind"))).alias("k")).select("d", "r", "p", "k.key", "k.kind")
    live = stage(rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("kind").alias("least")).where((F.col("n") > 1) & (F.col("least") == OWN)).select("key"), "live")
    rows = stage(rows.join(small(live, 500_000), "key", "left_semi"), "liverows")
    found = stage(signed(texts(docs, rows.select("d", "r", "p").distinct()), "x").select(F.struct("d", "r", "p").alias("at"), "x", "s1", "s2"), "lines")
    rows = rows.select(F.struct("d", "r", "p").alias("at"), "key", "kind").join(found.select("at", "s1", "s2"), "at")
    x, y = rows.alias("x"), rows.alias("y")
    a, b = F.col("x.at"), F.col("y.at")
    # That y is a line's own segment is said with both kinds: a filter on one side alone would be moved below the shuffle, which could not be shared then.
    alike = (F.col("x.key") == F.col("y.key")) & (F.col("x.kind") - F.col("y.kind") >= F.col("x.kind")) & (a != b) & ((F.col("x.kind") != OWN) | (a > b)) & may_be_near("x", "y", k)
    longer = F.col("x.kind") == SHORTER
    pairs = x.join(y, alike).select(F.when(longer, a).otherwise(F.greatest(a, b)).alias("a"), F.when(longer, b).otherwise(F.least(a, b)).alias("b"))
    pairs = stage(pairs.distinct(), "pairs")
    both = pairs.join(found.select(F.col("at").alias("a"), F.col("x").alias("xa")), "a").repartition(width(docs.sparkSession), "b").join(found.select(F.col("at").alias("b"), F.col("x").alias("xb")), "b")
    near = bounded_distance(both.where((F.length("xa") - F.length("xb")).between(0, k) & pieces_fit(F.col("xa"), F.col("xb"), k)), "xa", "xb", k).where(F.col("edits") <= k)
    return near.select(F.greatest("a", "b").alias("x")).select("x.*").distinct()


def copies_marked(rows: DataFrame, text: str) -> DataFrame:
    """rows with again, true for all but one row of each text, in place of false. Null texts stay false."""
    rows = stage(rows.drop("again").withColumns({"h": F.xxhash64(text), "at": F.monotonically_increasing_id()}), "noid")
    one = rows.where(F.col(text).isNotNull()).groupBy("h").agg(F.min("at").alias("at")).withColumn("one", F.lit(True))
    return rows.join(one, ["h", "at"], "left").withColumn("again", F.col(text).isNotNull() & F.col("one").isNull()).drop("h", "at", "one")


def dedup_lines(docs: DataFrame, edits: int = EDITS, min_chars: int = MIN_CHARS) -> DataFrame:
    """docs with text without repeated lines, and n_lines, n_copies, n_near (removed lines: exact and near copies), all long.

    Lines are what newlines part. A line with a word stays where it first occurs, by id and then position; later equal lines
    go, within a document and across documents. A first occurrence of min_chars characters or more goes, too, if it lies
    within edits of another one before it that is as long as that, whether or not that one stays. Lines without a word stay.
    Null text stays null and has no lines; empty text has one. Rows of equal id and text form one document: what one keeps, all
    keep. Rows of one id with different texts are documents of their own, in the order of a 64-bit hash of the text. Rows with null id are documents
    of their own, too, also if their texts are equal, and count after all others, in the order of that hash. A document that loses all its
    lines has an empty text. Other columns pass through, whatever their names; the added columns replace columns of their names.
    """
    added = ["n_lines", "n_copies", "n_near"]
    rows, names = hidden(docs, added)
    doc_id, text = names["doc_id"], names["text"]
    rows = rows.withColumn("again", F.lit(False))
    if not docs.where("doc_id is null").isEmpty():
        rows = rows.where(F.col(doc_id).isNotNull()).union(copies_marked(rows.where(F.col(doc_id).isNull()), text))
    d, r = F.coalesce(F.col(doc_id).cast("long"), F.lit(2**63 - 1)), F.xxhash64(text)
    plain = rows.where(~F.col("again") & F.col(text).isNotNull()).select(d.alias("d"), r.alias("r"), F.col(text).alias("t"))
    first = stage(owners(plain, edits, min_chars), "first")
    near = stage(near_copies(plain, first, edits), "near")
    mark = first.select("d", "r", "p").join(near.withColumn("m", F.lit(True)), ["d", "r", "p"], "left").groupBy("d", "r").agg(F.sort_array(F.collect_list(F.when(F.col("m").isNull(), F.col("p")))).alias("keep"), F.count("m").alias("near"))
    # A row that copies one with null id meets no mark.
    out = rows.withColumns({"d": F.when(~F.col("again"), d), "r": r}).join(mark.hint("shuffle_hash"), ["d", "r"], "left").withColumn("ls", F.split(text, "\n"))
    out = out.withColumn("kept", F.filter("ls", lambda x, i: ~worded(x) | F.coalesce(F.array_contains("keep", i), F.lit(False))))
    n = lambda c: F.when(F.col("ls").isNull(), 0).otherwise(c).cast("long")
    near_ = F.coalesce("near", F.lit(0))
    return out.select(*shown(names, text=F.array_join("kept", "\n")), n(F.size("ls")).alias("n_lines"), n(F.size("ls") - F.size("kept") - near_).alias("n_copies"), near_.cast("long").alias("n_near"))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_copies", "n_near", F.length("text").cast("long").alias("n_chars"), F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"))

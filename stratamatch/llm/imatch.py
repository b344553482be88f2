"""I-Match fingerprints over randomised lexicon subsets, with DataFrame functions only.

The lexicon is the terms whose inverse document frequency lies in a band: a term of
more than ``1 / commonest`` of the documents is left out (at most ``commonest`` times
the distinct terms of a mean document are so common, which bounds what is broadcast;
the size is checked), and there is no upper end. The lexicon falls into random subsets
of densities 1/16, 1/32, ...: eight of each. A document's distinct terms in a subset
are sorted and hashed together. A fingerprint is the list of subset hashes (blank: no
term there). Short documents speak through dense subsets, long ones through sparse ones.

Likeness is the share of subsets whose hashes agree, over those densities at which the
smaller of the two documents fills at most three quarters of the subsets.

Defined results: null text is empty; a document without a term in the band is
fingerprinted by all its terms; two documents without any terms are alike (1).
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .durable import stored

COMMONEST, LEVELS, EACH, BROADCAST_ROWS, RANGE_BYTES = 50, 13, 8, 2_000_000, 4 << 20
_WIDTH = 6


def terms(text: Column) -> Column:
    """Distinct lower-case terms of a text column."""
    spaced = F.translate(F.lower(text), "\t\n\x0b\x0c\r", "     ")
    return F.array_remove(F.array_distinct(F.split(spaced, " +")), "")


def common_terms(texts: DataFrame, n: int, commonest: int = COMMONEST) -> DataFrame:
    """Hashes of the terms in at least 1/``commonest`` of the ``n`` documents (two at least)."""
    counted = texts.select(F.explode(terms(F.col("text"))).alias("t")).select(F.xxhash64("t").alias("term")).groupBy("term").agg(F.count("*").alias("df"))
    return counted.where(F.col("df") >= max(2, -(-n // commonest))).select("term")


def cell_of(term: Column) -> Column:
    """Subset of a term hash: level (trailing zeros of a second hash) and one of eight in it."""
    h = F.xxhash64(term, F.lit(17))
    g = F.shiftrightunsigned(h, 1)
    level = F.least(F.bit_count(g.bitwiseXOR(g - 1)) - 1, F.lit(LEVELS - 1))
    return (level * EACH + F.shiftright(h, 40).bitwiseAND(EACH - 1)).cast("int")


def subset_codes(texts: DataFrame, common: DataFrame, keys: list[str]) -> DataFrame:
    """``keys``, kind, cell, code and x (hash of its sorted terms), n for every row of (keys,
    kind, text) and subset that it has terms in; cell -1 holds common terms, -2 means no term.
    If ``keys`` include the column by which ``texts`` is dealt, nothing is shuffled."""
    small = common.count() <= BROADCAST_ROWS
    rows = texts.select(*keys, "kind", F.explode_outer(terms(F.col("text"))).alias("t"))  # a row also for no term
    rows = rows.select(*keys, "kind", F.when(F.col("t").isNotNull(), F.xxhash64("t")).alias("term"))
    common = common.withColumn("is_common", F.lit(True))
    rows = rows.join(F.broadcast(common) if small else common, "term", "left")
    cell = F.when(F.col("term").isNull(), -2).when(F.col("is_common"), -1).otherwise(cell_of(F.col("term"))).cast("int")
    cells = rows.select(*keys, "kind", "term", cell.alias("cell")).groupBy(*keys, "kind", "cell").agg(F.xxhash64(F.array_sort(F.collect_list("term")), F.lit(29)).alias("x"), F.count("term").alias("n"))
    return cells.withColumn("code", F.substring(F.lpad(F.hex(F.xxhash64("x", "n")), 16, "0"), 1, _WIDTH))


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def listed(found: Column) -> Column:
    """Codes of all subsets in order (empty: no term there) from the (cell, code, x, n) of a text;
    one code of all terms if none is in a subset."""
    inside = F.filter(found, lambda z: z["cell"] >= 0)
    slots = F.sequence(F.lit(0), F.lit(LEVELS * EACH - 1))

    def codes(z):
        m = F.map_from_entries(F.transform(z, lambda e: F.struct(e["cell"], e["code"])))
        return _let(m, lambda by: F.transform(slots, lambda i: F.coalesce(F.try_element_at(by, i), F.lit(""))))

    total = F.aggregate(found, F.struct(F.lit(0).cast("long").alias("x"), F.lit(0).cast("long").alias("n")), lambda acc, z: F.struct(acc["x"].bitwiseXOR(F.coalesce(z["x"], F.lit(0))).alias("x"), (acc["n"] + z["n"]).alias("n")))
    plain = _let(total, lambda t: F.array(F.when(t["n"] == 0, F.lit("none")).otherwise(F.concat(F.lit("all"), F.hex(F.xxhash64(t["x"], t["n"]))))))
    return _let(inside, lambda z: F.when(F.size(z) > 0, codes(z)).otherwise(plain))


def as_text(codes: Column) -> Column:
    return F.array_join(F.transform(codes, lambda c: F.when(c == "", F.lit("-" * _WIDTH)).otherwise(c)), "")


def likeness(a: Column, b: Column) -> Column:
    """Likeness from 0 to 1 of two lists of codes."""
    pairs = F.zip_with(a, b, lambda x, y: F.when((x != "") & (x == y), 3).otherwise((x != "").cast("int") + 16 * (y != "").cast("int")))
    # Per level: how many subsets each fills, and how many agree, in one number: a + 16 b + 256 same.
    number = F.transform(pairs, lambda p: F.when(p == 3, F.lit(1 + 16 + 256)).otherwise(p))
    starts = F.sequence(F.lit(0), F.lit(LEVELS - 1))
    levels = _let(number, lambda z: F.transform(starts, lambda k: reduce(add, (F.get(z, k * EACH + i) for i in range(EACH)))))
    least = lambda z: F.least(z.bitwiseAND(15), F.shiftright(z, 4).bitwiseAND(15))
    total = F.aggregate(levels, F.lit(0), lambda acc, z: acc + F.when(least(z) <= EACH * 3 // 4, least(z) + 4096 * F.shiftright(z, 8)).otherwise(0))
    share = _let(total, lambda t: F.when(t.bitwiseAND(4095) > 0, F.shiftright(t, 12) / t.bitwiseAND(4095)).otherwise(0.0))
    return F.when(a == b, F.lit(1.0)).when((F.size(a) > 1) & (F.size(b) > 1), share).otherwise(F.lit(0.0))


def with_next(rows: DataFrame, key: str, tie: str, carry: str, ranges: int = 1) -> DataFrame:
    """``rows`` with range, place, own and next_<carry>: the value of ``carry`` at the next row in
    descending order of (key, tie), nulls last; after the last the first. Rows are dealt to ranges
    (``ranges`` or the session's setting, if more) cut at quantiles, each a window of its own; the last row of each range also goes to the next
    range as its first row (own = 0), so a row's next one always has the place before it."""
    spark = rows.sparkSession
    n = max(1, min(max(int(spark.conf.get("spark.sql.shuffle.partitions")), ranges), 10_000))
    cuts = rows.agg(F.percentile_approx(key, [i / n for i in range(1, n)], 20 * n)).first()[0] if n > 1 else None
    cuts = sorted(set(cuts or []))
    steps = F.array(*(F.lit(2**i) for i in range(max(len(cuts), 1).bit_length(), -1, -1)))
    bounds = F.array(*(F.lit(c).cast("long") for c in cuts)) if cuts else F.array(F.lit(None).cast("long"))
    found = F.aggregate(steps, F.lit(0), lambda acc, s: F.when(F.get(bounds, acc + s - 1) <= F.col(key), acc + s).otherwise(acc))
    range_ = F.coalesce(found, F.lit(0))
    dealt = rows.withColumn("range", range_)
    tops = sorted((tuple(r) for r in dealt.groupBy("range").agg(F.max(F.struct(key, tie)).alias("t")).select("range", f"t.{key}", f"t.{tie}").collect()), key=lambda r: r[0])  # one row a range
    goes = [(t[1], t[2], tops[(i + 1) % len(tops)][0]) for i, t in enumerate(tops)]
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    table = F.broadcast(spark.createDataFrame(goes, f"top_key {kinds[key]}, top_tie {kinds[tie]}, goes_to int"))
    guests = rows.join(table, F.col(key).eqNullSafe(F.col("top_key")) & F.col(tie).eqNullSafe(F.col("top_tie")))
    # Rows that repeat a range's last row are all equal; one of them is enough.
    guests = guests.dropDuplicates(["goes_to"]).select(F.col("goes_to").alias("range"), F.lit(0).alias("own"), *rows.columns)
    order = Window.partitionBy("range").orderBy("own", F.col(key).asc_nulls_first(), tie)
    out = guests.unionByName(dealt.select("range", F.lit(1).alias("own"), *rows.columns))
    if ranges > 1:  # so many tasks, not as many as the bytes of the texts ask: what follows makes a row of each term
        out = out.repartition(n, "range")
    return out.select("*", F.row_number().over(order).alias("place"), F.lag(carry).over(order).alias(f"next_{carry}"))


def fingerprint_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.
    Texts are shuffled once, by range of id; all later groups and windows keep that dealing."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    count, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    common = stored(common_terms(rows.select("text"), count), "common-terms")
    rows = with_next(rows.withColumn("tie", F.xxhash64("text")), "id", "tie", "text", -(-size // RANGE_BYTES))
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.coalesce("next_text", F.lit("")), F.lit(1), half))
    rows = rows.select("range", "place", "own", "id", n.cast("long").alias("n_chars"), "text", edited.alias("edited"))
    both = F.array(F.struct(F.lit(0).alias("kind"), F.col("text").alias("text")), F.struct(F.lit(1).alias("kind"), F.col("edited").alias("text")))
    keys = ["range", "place", "own", "id", "n_chars", "sha"]
    both = rows.select(*keys[:-1], F.unhex(F.sha2(F.col("edited").cast("binary"), 256)).alias("sha"), F.explode(both).alias("of")).select(*keys, "of.kind", "of.text")
    cells = subset_codes(both, common, keys)
    prints = cells.groupBy(*keys).agg(F.collect_list(F.struct("kind", "cell", "code", "x", "n")).alias("found"))
    of = lambda kind: listed(F.filter("found", lambda z: z["kind"] == kind))
    prints = prints.select(*keys, of(0).alias("codes"), of(1).alias("edited_codes"))
    prints = prints.withColumn("next_codes", F.lag("codes").over(Window.partitionBy("range").orderBy("place"))).where("own = 1")
    return prints.select(
        F.col("id").alias(id_col), "n_chars", F.lower(F.hex("sha")).alias("edited_sha256"), as_text(F.col("codes")).alias("fingerprint"), as_text(F.col("edited_codes")).alias("edited_fingerprint"),
        likeness(F.col("codes"), F.col("edited_codes")).alias("near_edited"), likeness(F.col("codes"), F.col("next_codes")).alias("near_next"),
    )

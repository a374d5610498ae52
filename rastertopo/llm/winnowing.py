"""Document fingerprints by winnowing, in DataFrame operations only.

Each gram is k successive characters (code points), white space included. Of each window of w successive grams the
smallest hash is chosen, of equal ones the rightmost, and kept with its position. So two texts that share k + w - 1
successive characters share a fingerprint entry, at positions that the entries tell.

A chosen entry is one long: 38 bits of hash above 25 bits that fall as the position rises, so that the least long of a
window is the rightmost least hash. A text of under k characters is one gram; positions past 2**25 characters count as
that position.

Cases: a null text counts as empty; equal texts have equal fingerprints; an empty table gives an empty result; columns
other than the id and the text are ignored. Rows that share a doc_id follow each other in the order of their texts;
a null doc_id comes last, its neighbours found likewise.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_or_empty

GRAM, WINDOW = 8, 8
POSITION_BITS = 25
HASH_MASK, POSITION_MASK = (1 << 38) - 1, (1 << POSITION_BITS) - 1
#: Rows of one stretch of the id order, and the most stretches (their bounds are literals of the plan).
STRETCH_ROWS, MOST_STRETCHES = 500, 1024
LEAST = -(1 << 63)


def chosen(text: Column, k: int = GRAM, w: int = WINDOW) -> Column:
    """array<long>: the packed entries of a text's fingerprint in text order."""
    # One match for each code point; the gram is what its lookahead sees.
    found = F.regexp_extract_all(text, F.lit(f"(?s)(?=(.{{{k}}}))."), F.lit(1))
    grams = F.when(F.length(text) < k, F.array(text)).otherwise(found)

    def packed(gram: Column, i: Column) -> Column:
        return F.shiftleft(F.xxhash64(gram).bitwiseAND(F.lit(HASH_MASK)), POSITION_BITS).bitwiseOR(F.lit(POSITION_MASK) - F.least(i, F.lit(POSITION_MASK)))

    def wider(step: int):
        # Past the end there is nothing to be less.
        return lambda x: F.zip_with(x, F.slice(x, step + 1, F.size(x)), lambda a, b: F.least(a, b))

    least, width = F.transform(grams, packed), 1
    while width < w:
        step = min(width, w - width)
        least = _let(least, wider(step))
        width += step
    # The last w - 1 windows are not whole.
    return F.array_distinct(_let(least, lambda x: F.slice(x, F.lit(1), F.greatest(F.size(x) - w + 1, F.lit(1)))))


def _let(value: Column, body) -> Column:
    """``body`` applied to a value that is computed once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _hash(entry: Column) -> Column:
    return F.shiftright(entry, POSITION_BITS)


def _position(entry: Column) -> Column:
    return F.lit(POSITION_MASK) - entry.bitwiseAND(F.lit(POSITION_MASK))


def leading(entries: Column, n: Column, k: int = GRAM, w: int = WINDOW) -> Column:
    """The entries of a text's first ``n`` characters, k + w - 1 or more, out of those of the whole text.

    An entry is chosen from the window that ends with its gram, or, where the entry before is less, from the window that
    starts after that one; so it needs no more than one look back to tell if a whole window of the part chose it."""
    last = n - (k + w - 1)

    def inside(e, i):
        before = F.get(entries, i - 1)
        return (_position(e) <= last) | ((_position(e) <= n - k) & ((i == 0) | (_hash(e) <= _hash(before)) | (_position(before) < last)))

    return F.filter(entries, inside)


def spliced(text: Column, entries: Column, kept: Column, other: Column, other_entries: Column, taken: Column, k: int = GRAM, w: int = WINDOW) -> Column:
    """The entries of the first ``kept`` characters of a text followed by the first ``taken`` of another, of which the
    entries are known: only the windows over the seam are hashed. Short parts, and positions that stop, take the plain way."""
    side = k + w - 2
    seam = chosen(F.concat(F.substr(text, kept - side + 1, F.lit(side)), F.substr(other, F.lit(1), F.lit(side))), k, w)
    moved = lambda found, by: F.transform(found, lambda e: e - by)
    parts = F.concat(leading(entries, kept, k, w), moved(seam, (kept - side).cast("long")), moved(leading(other_entries, taken, k, w), kept.cast("long")))
    plain = chosen(F.concat(F.substr(text, F.lit(1), kept), F.substr(other, F.lit(1), taken)), k, w)
    return F.when((kept > side) & (taken > side) & (kept + taken < POSITION_MASK), F.array_distinct(parts)).otherwise(plain)


def hashes_of(entries: Column) -> Column:
    return F.array_distinct(F.transform(entries, lambda x: F.shiftright(x, POSITION_BITS)))


def as_string(entries: Column) -> Column:
    """The entries as hash@position, hash in hexadecimal, position counted in characters from 0."""
    one = lambda x: F.concat(F.hex(F.shiftright(x, POSITION_BITS)), F.lit("@"), (F.lit(POSITION_MASK) - x.bitwiseAND(F.lit(POSITION_MASK))).cast("string"))
    return F.array_join(F.transform(entries, one), " ")


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two arrays of distinct hashes."""
    common = F.size(F.array_intersect(a, b))
    return common / (F.size(a) + F.size(b) - common)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = GRAM, w: int = WINDOW) -> DataFrame:
    """The general operator: (id, entries array<struct<hash, position>>, fingerprint)."""
    entries = docs.select(F.col(id_col), chosen(text_or_empty(text_col), k, w).alias("_e"))
    split = F.transform("_e", lambda x: F.struct(F.shiftright(x, POSITION_BITS).alias("hash"), (F.lit(POSITION_MASK) - x.bitwiseAND(F.lit(POSITION_MASK))).alias("position")))
    return entries.select(id_col, split.alias("entries"), as_string(F.col("_e")).alias("fingerprint"))


def with_next(rows: DataFrame, key: str, tie: list[str], carried: dict[str, Column]) -> DataFrame:
    """Adds next_<name> for each carried expression: its value on the next row by descending ``key`` (after the last: the first).

    The key order is cut into stretches at approximate quantiles; the head of a stretch also travels, as a ghost, to the
    stretch before it, so that one shuffle suffices and no task gets more than some stretches."""
    ids = rows.select(key)
    n = ids.count()
    if n == 0:
        bounds, heads = [], [(0, 0)]
    else:
        parts = max(1, min(MOST_STRETCHES, n // STRETCH_ROWS))
        cuts = [i / parts for i in range(1, parts)]
        bounds = sorted(set(ids.agg(F.percentile_approx(key, cuts, 10 * MOST_STRETCHES)).first()[0])) if cuts else []
        heads = []
    stretch = F.size(F.filter(F.array(*[F.lit(b) for b in bounds]), lambda b: b < F.col(key))) if bounds else F.lit(0)
    if n:
        heads = sorted(tuple(r) for r in ids.groupBy(stretch.alias("_s")).agg(F.max(key)).collect())
    # The head of a stretch follows the last row of the next higher one; the highest stretch's head follows the lowest.
    towards = {s: heads[(i + 1) % len(heads)][0] for i, (s, _) in enumerate(heads)}
    head_of = F.create_map(*[F.lit(x) for s, h in heads for x in (s, h)])
    ghost_to = F.create_map(*[F.lit(x) for s, t in towards.items() for x in (s, t)])
    own = F.struct(F.col("_s").alias("s"), F.lit(False).alias("ghost"))
    ghost = F.when(F.col(key) == head_of[F.col("_s")], F.struct(ghost_to[F.col("_s")].alias("s"), F.lit(True).alias("ghost")))
    spread = rows.withColumn("_s", stretch).withColumn("_at", F.explode(F.array_compact(F.array(own, ghost))))
    spread = spread.withColumn("_s", F.col("_at.s")).withColumn("_ghost", F.col("_at.ghost")).drop("_at")
    order = [F.col("_ghost"), F.col(key).desc(), *[F.col(x) for x in tie]]
    near = spread.repartition("_s").sortWithinPartitions("_s", *order)
    for name, value in carried.items():
        near = near.withColumn(name, value)
    window = Window.partitionBy("_s").orderBy(*order)
    return near.select("*", *[F.lead(name).over(window).alias(f"next_{name}") for name in ["text", *carried]]).filter(~F.col("_ghost")).drop("_s", "_ghost")


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = GRAM, w: int = WINDOW) -> DataFrame:
    """Fingerprints of each text and of its edited text, and the likeness to the edited and to the next text."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    rows = rows.withColumn("_key", F.coalesce("doc_id", F.lit(LEAST)))
    near = with_next(rows, "_key", ["text"], {"entries": chosen(F.col("text"), k, w)})
    near = near.withColumn("n_chars", F.length("text").cast("long")).withColumn("_cut", F.floor(F.col("n_chars") / 2).cast("int"))
    near = near.withColumn("_kept", (F.col("n_chars") - F.col("_cut")).cast("int")).withColumn("_taken", F.least("_cut", F.length("next_text")))
    edited = F.concat(F.substr(F.col("text"), F.lit(1), F.col("_kept")), F.substr(F.col("next_text"), F.lit(1), F.col("_taken")))
    edited_entries = spliced(F.col("text"), F.col("entries"), F.col("_kept"), F.col("next_text"), F.col("next_entries"), F.col("_taken"), k, w)
    near = near.withColumn("edited", edited).withColumn("edited_entries", edited_entries)
    near = near.withColumn("own", hashes_of(F.col("entries")))
    return near.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        as_string(F.col("entries")).alias("fingerprint"),
        as_string(F.col("edited_entries")).alias("edited_fingerprint"),
        likeness(F.col("own"), hashes_of(F.col("edited_entries"))).alias("near_edited"),
        likeness(F.col("own"), hashes_of(F.col("next_entries"))).alias("near_next"),
    )

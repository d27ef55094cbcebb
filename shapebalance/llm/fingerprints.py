"""Document fingerprints from spots: chains of content words behind common-word anchors, in DataFrame functions only.

A common word opens a spot; its signature is the anchor with the next `chain` content words, common words skipped.
Stretches of content words longer than `reach` open spots of their own, so that texts without common words have
signatures as well. A text's fingerprint is its set of signature hashes; two are compared by Jaccard likeness.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import parts

# Common words of English, French, German and Spanish.
COMMON = (
    "the of and a to in is it you that he was for on are with as i his they be at one have this from or had by not but what all were we when your can said there an each which she do how their if "
    "le la les de des du un une et en est que qui dans pour par sur au aux il elle ne pas ce se son sa avec plus ou mais nous vous leur "
    "der die das und ist von zu den mit sich auf für nicht ein eine als auch es dem werden aus er hat dass sie nach wird bei einer um am sind noch wie einem über so zum war haben nur oder aber vor zur bis mehr durch man "
    "el los las y del por con una su para como más o pero sus al lo ha sin sobre este ya entre cuando todo esta ser son dos también fue había era muy hasta desde está mi porque"
).split()


@dataclass(frozen=True)
class SpotConfig:
    common: tuple[str, ...] = tuple(dict.fromkeys(COMMON))
    #: Content words in a chain, content words after which a stretch opens a spot of its own, spots that a chain may run over.
    chain: int = 3
    reach: int = 6
    over: int = 4


_MARK = "\u0001"


def signatures(text: Column, c: SpotConfig = SpotConfig()) -> Column:
    """The set of signature hashes of a text, as array<bigint> without repeats. Text without words has its own hash; null and empty text none."""
    words = F.split(F.regexp_replace(F.lower(text), r"[\s\p{Punct}\x{01}«»¿¡…–—]+", " "), " ")
    marked = F.array_join(F.transform(words, lambda w: F.when(w.isin(*c.common), F.concat(F.lit(_MARK), w)).otherwise(w)), " ")
    # an anchor with up to `reach` content words, or such words alone
    spot = rf"\x01\S+(?: [^\x01 ]\S*){{0,{c.reach}}}|[^\x01 ]\S*(?: [^\x01 ]\S*){{0,{c.reach - 1}}}"
    spots = F.regexp_extract_all(marked, F.lit(spot), F.lit(0))

    def signature(s: Column, i: Column, all_spots: Column) -> Column:
        behind = F.array_join(F.slice(all_spots, i + 2, c.over), " ")
        anchored = s.startswith(_MARK)
        anchor = F.when(anchored, F.substring_index(s, " ", 1)).otherwise("")
        content = F.regexp_replace(F.concat_ws(" ", s, behind), r"\x01\S+ ?", "")
        return F.xxhash64(anchor, F.substring_index(content, " ", c.chain))

    # a one-element array binds the list of spots once; nested, it would be built for each spot
    bound = F.flatten(F.transform(F.array(spots), lambda a: F.transform(a, lambda s, i: signature(s, i, a))))
    made = F.array_distinct(bound)
    whole = F.coalesce(text, F.lit(""))
    alone = F.when(whole == "", F.expr("array()").cast("array<bigint>")).otherwise(F.array(F.xxhash64(whole)))
    # bound once again, so that the set is built once
    return F.flatten(F.transform(F.array(made), lambda m: F.when(F.size(m) > 0, m).otherwise(alone)))


def likeness(a: Column, b: Column) -> Column:
    """Jaccard likeness of two signature sets; 1 for two empty ones. Where one is empty nothing is compared."""
    both = F.size(F.array_intersect(a, b))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), 1.0).when((F.size(a) == 0) | (F.size(b) == 0), 0.0).otherwise(both / (F.size(a) + F.size(b) - both))


def digest(sigs: Column) -> Column:
    """A signature set in short: its size and a 128-bit hash of its sorted elements."""
    return F.concat_ws(":", F.size(sigs).cast("string"), F.md5(F.array_join(F.array_sort(sigs).cast("array<string>"), ",").cast("binary")))


def in_ranges(docs: DataFrame) -> DataFrame:
    """doc_id, text ('' for null), at, tie, range, guest: the rows in ranges of doc_id, each with a guest row after its last.

    Percentiles of doc_id, which are values of it, cut the table in ranges. The row that opens a range is also the guest
    of the range before, and the first row that of the last range, so that each range knows its last row's successor and
    text moves once. A null doc_id sorts first; rows that repeat one are ordered by the text's hash (`tie`).
    """
    least = -(1 << 63)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("at", F.coalesce("doc_id", F.lit(least)))
    n = 4 * parts(docs.sparkSession)
    cuts = rows.agg(F.percentile_approx("at", [i / n for i in range(n)], 100 * n).alias("p")).first()["p"] or [least]
    cuts = sorted(set(cuts))
    bounds = F.array(*[F.lit(x).cast("long") for x in cuts])
    own = F.size(F.filter(bounds, lambda x: x <= F.col("at"))) - 1
    before = F.when(F.col("at") == cuts[0], len(cuts) - 1).otherwise(F.col("own") - 1)
    here, there = F.struct(F.col("own").alias("range"), F.lit(0).alias("guest")), F.struct(before.cast("int").alias("range"), F.lit(1).alias("guest"))
    places = F.when(F.array_contains(bounds, F.col("at")), F.array(here, there)).otherwise(F.array(here))
    placed = rows.withColumn("own", own).withColumn("place", F.explode(places))
    return placed.select("doc_id", "text", "at", F.xxhash64("text").alias("tie"), "place.range", "place.guest")


def edited_fingerprints(docs: DataFrame, c: SpotConfig = SpotConfig()) -> DataFrame:
    """Fingerprints of every row's text, of its edited text, and their likeness; and the likeness to the next document.

    The edited text has its last floor(n / 2) code points replaced by the first as many (or all) of the next document by
    doc_id, after the last the first. Null text counts as empty; two empty texts have likeness 1. Rows that repeat a
    doc_id follow one another; a single row is its own successor; an empty table gives an empty one; other columns are
    ignored. One shuffle of the texts, by ranges of doc_id; both windows share it and its sort.
    """
    w = Window.partitionBy("range").orderBy("guest", "at", "tie")
    rows = in_ranges(docs).withColumn("next", F.coalesce(F.lead("text").over(w), F.col("text")))
    rows = rows.withColumn("half", F.expr("CAST(char_length(text) DIV 2 AS INT)"))
    rows = rows.withColumn("edited", F.concat(F.expr("left(text, CAST(char_length(text) AS INT) - half)"), F.expr("left(next, half)")))
    sets = rows.select(
        "doc_id", "range", "guest", "at", "tie", F.char_length("text").cast("long").alias("n_chars"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        signatures(F.col("text"), c).alias("t"), signatures(F.col("edited"), c).alias("e"),
    )
    sets = sets.withColumn("n", F.coalesce(F.lead("t").over(w), F.col("t"))).where("guest = 0")
    return sets.select("doc_id", "n_chars", "edited_sha256", digest(F.col("t")).alias("fingerprint"), digest(F.col("e")).alias("edited_fingerprint"), likeness(F.col("t"), F.col("e")).alias("near_edited"), likeness(F.col("t"), F.col("n")).alias("near_next"))


def fingerprints(docs: DataFrame, c: SpotConfig = SpotConfig()) -> DataFrame:
    """doc_id, signatures array<bigint>, fingerprint of every row (null text: empty set). Narrow."""
    return docs.select("doc_id", signatures(F.col("text"), c).alias("signatures")).select("doc_id", "signatures", digest(F.col("signatures")).alias("fingerprint"))


def near_pairs(docs: DataFrame, least: float = 0.8, c: SpotConfig = SpotConfig()) -> tuple[DataFrame, DataFrame]:
    """Links (a, b, likeness) of at least `least` between classes of equal fingerprints, and members (doc_id, class), a class being its smallest doc_id.

    Sets are partitioned by length so that likeness `least` reaches the next partition at most. Inside and across two
    neighbours a class meets others through its rarest signatures alone, n - ceil(least * n) + 1 of n, of which two sets
    alike enough always share one; a pair whose sizes exclude the likeness is dropped before its sets are compared.
    Null doc_ids and texts without signatures take no part. Repeated rows are one member each; an empty table gives
    empty ones. The work grows with the links between different texts, which are the result; exact copies add none.
    """
    sets = fingerprints(docs.where("doc_id IS NOT NULL"), c).where(F.size("signatures") > 0)
    classes = sets.groupBy("fingerprint").agg(F.min("doc_id").alias("class"), F.first("signatures").alias("signatures"))
    members = sets.select("doc_id", "fingerprint").join(classes.select("fingerprint", "class"), "fingerprint").select("doc_id", "class")
    sized = classes.select("class", "signatures", F.size("signatures").alias("n")).withColumn("part", F.floor(F.log("n") / F.log(F.lit(1 / least)) / 1.000001).cast("int"))
    rows = sized.select("class", "n", "part", F.explode("signatures").alias("s"))
    often = rows.groupBy("s").agg(F.count("*").alias("often"))
    place = F.row_number().over(Window.partitionBy("class").orderBy("often", "s"))
    rare = rows.join(often, "s").withColumn("place", place).where(F.col("place") <= F.col("n") - F.ceil(F.col("n") * least - 1e-9) + 1)
    a = rare.select(F.col("class").alias("a"), F.col("n").alias("na"), "s", F.explode(F.array("part", F.col("part") + 1)).alias("part"), F.col("part").alias("pa"))
    b = rare.select(F.col("class").alias("b"), F.col("n").alias("nb"), "s", "part")
    fits = (F.least("na", "nb") >= least * F.greatest("na", "nb")) & ((F.col("pa") < F.col("part")) | (F.col("a") < F.col("b")))
    pairs = a.join(b, ["s", "part"]).where(fits & (F.col("a") != F.col("b"))).select("a", "b").distinct()
    whole = lambda k: sized.select(F.col("class").alias(k), F.col("signatures").alias(f"s{k}"))
    found = pairs.join(whole("a"), "a").join(whole("b"), "b").withColumn("likeness", likeness(F.col("sa"), F.col("sb"))).where(F.col("likeness") >= least)
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "likeness"), members

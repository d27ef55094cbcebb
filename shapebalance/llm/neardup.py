"""Near-duplicate documents: MinHash bands propose pairs, sequential Bayesian verification prunes them, full sets confirm.

Equal word sequences are one class from the start, so that groups of exact copies cost one row each. Within a band's
bucket, of whatever size, every class is compared with the bucket's leader, the class that sits in the fullest buckets.
Where followers of one leader stay in several groups after that, each that its leader does not link is compared with
those of other groups. Signature batches are compared and pruned as before. Survivors are verified exactly through the
shingles D by which each differs from the leader: x and y differ by |D(x)| + |D(y)| - 2 |D(x) & D(y)|, so what near
copies of one text have in common costs nothing. Followers go to tasks in blocks, which return links, one for two
groups; so no bucket emits its pairs, and no link is lost to a cap.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Work, semi_join, spread_join, text_bytes, text_slices
from .components import components
from .hashing import MinHash, combine, mix, shingles, span_hashes, stream, word_spans


@dataclass(frozen=True)
class NearDupConfig:
    #: Words in a shingle; two sets are linked from `percent` hundredths of likeness on.
    words: int = 5
    percent: int = 80
    #: Bands of rows of signature values: a pair at 0.8 shares no band with probability (1 - 0.8^4)^32 < 1e-7.
    bands: int = 32
    rows: int = 4
    #: Signature values that are compared at a time.
    batch: int = 32
    #: A pair is pruned when the posterior probability of being alike enough falls below this.
    miss: float = 1e-7
    #: Followers that go to one task beside a copy of their leader.
    beside: int = 256
    #: Shingles (or followers) in a block of the comparison among followers.
    block: int = 500_000


def least_matches(n: int, t: float, miss: float) -> int:
    """Fewest of n matching values at which likeness >= t keeps a posterior probability of at least `miss`.

    Under a uniform prior the posterior after m matches is Beta(m + 1, n - m + 1), whose upper tail at t is the chance
    that a binomial count of n + 1 trials with probability t is at most m.
    """
    tail = 0.0
    for m in range(n + 1):
        tail += math.comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
        if tail >= miss:
            return m
    return n + 1


def _word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    values, offsets = text_bytes(column)
    starts, ends, at = word_spans(values, offsets)
    return span_hashes(values, starts, ends), at


@cache
def _permutations(n: int) -> MinHash:
    return MinHash(n)


def _sign(c: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        minhash = _permutations(c.bands * c.rows)
        salt = stream(31, c.bands)
        for b in text_slices(batches):
            words, at = _word_hashes(b.column("text"))
            n = b.num_rows
            sizes, keys = np.zeros(n, np.int64), [b""] * n
            signature = np.zeros((n, c.bands * c.rows), np.uint64)
            for i in range(n):
                own = words[at[i] : at[i + 1]]
                if len(own):
                    s = shingles(own, c.words)
                    sizes[i], keys[i], signature[i] = len(s), xxhash.xxh3_128_digest(own.tobytes()), minhash(s)
            bands = mix(combine(list(np.moveaxis(signature.reshape(n, c.bands, c.rows), 2, 0))) + salt).view(np.int64)
            sketch = (mix(signature) & np.uint64(0xFFFF)).astype("<u2")
            yield pa.record_batch(
                [
                    b.column("doc_id"),
                    pa.array(sizes),
                    pa.array(keys, pa.binary()),
                    pa.FixedSizeBinaryArray.from_buffers(pa.binary(2 * c.bands * c.rows), n, [None, pa.py_buffer(sketch.tobytes())]).cast(pa.binary()),
                    pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * c.bands), pa.array(bands.ravel())),
                ],
                ["doc_id", "n_shingles", "key", "sketch", "bands"],
            )

    return run


def _prune(c: NearDupConfig):
    """Of a stream of leaders (b null) and their followers with sketches, the pairs whose posterior stays above `miss` batch after batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = c.bands * c.rows
        least = [(k, least_matches(k, c.percent / 100, c.miss)) for k in range(c.batch, n + 1, c.batch)]
        last = np.zeros((1, n), np.uint16)
        for b in batches:
            if not b.num_rows:
                continue
            sketch = np.concatenate([last, np.frombuffer(b"".join(b.column("v").to_pylist()), "<u2").reshape(-1, n)])
            leads = np.concatenate([[True], np.asarray(b.column("b").is_null())])
            leader = np.maximum.accumulate(np.where(leads, np.arange(len(leads)), 0))
            alive = np.flatnonzero(~leads)
            matches = np.zeros(len(leads), np.int64)
            done = 0
            for k, m in least:
                matches[alive] += (sketch[alive, done:k] == sketch[leader[alive], done:k]).sum(axis=1)
                alive = alive[matches[alive] >= m]
                done = k
            last = sketch[leader[-1:]].copy()
            kept = pa.array(alive - 1)
            yield pa.record_batch([b.column("a").take(kept), b.column("b").take(kept)], ["a", "b"])

    return run


def _sets(c: NearDupConfig, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, int, np.ndarray, np.ndarray]]:
    """Of a stream of leaders (b null) and their followers with texts: a batch, a follower's row, its leader's set, its own set."""
    lead = np.zeros(0, np.uint64)
    for b in text_slices(batches, "v"):
        words, at = _word_hashes(b.column("v"))
        leads = np.asarray(b.column("b").is_null())
        for i in range(b.num_rows):
            own = shingles(words[at[i] : at[i + 1]], c.words)
            if leads[i]:
                lead = own
            else:
                yield b, i, lead, own


def _alike(c: NearDupConfig, p: np.ndarray, q: np.ndarray) -> bool:
    both = len(np.intersect1d(p, q, assume_unique=True))
    return 100 * both >= c.percent * (len(p) + len(q) - both)


def _batched(rows: Iterator[tuple], schema: pa.Schema, limit: int) -> Iterator[pa.RecordBatch]:
    """Rows, each with its weight in front, in record batches of about `limit` weight."""
    out, weight = [], 0
    for w, *row in rows:
        out.append(row)
        weight += w
        if weight >= limit:
            yield pa.record_batch([pa.array(x, t) for x, t in zip(zip(*out, strict=True), schema.types, strict=True)], schema=schema)
            out, weight = [], 0
    if out:
        yield pa.record_batch([pa.array(x, t) for x, t in zip(zip(*out, strict=True), schema.types, strict=True)], schema=schema)


def _confirm(c: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = ((1, b.column("a")[i].as_py(), b.column("b")[i].as_py()) for b, i, p, q in _sets(c, batches) if _alike(c, p, q))
        yield from _batched(hits, pa.schema([("a", pa.int64()), ("b", pa.int64())]), 10_000)

    return run


_DIFFERENCES = "a long, b long, g long, probe boolean, linked boolean, size long, d long, sketch binary, shingles binary"
_BLOCK = ("b", "g", "probe", "size", "d")
_BLOCKS = "a long, block long, asks boolean, " + ", ".join(f"{x} binary" for x in (*_BLOCK, "sketch", "shingles"))


def _differ(c: NearDupConfig):
    """Of a stream of leaders and followers with texts: by what each follower differs from its leader.

    A follower in another group than its leader's is linked to it, or a probe, to be compared with other followers.
    """
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("g", pa.int64()), ("probe", pa.bool_()), ("linked", pa.bool_()), ("size", pa.int64()), ("d", pa.int64()), ("sketch", pa.binary()), ("shingles", pa.binary())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for b, i, lead, own in _sets(c, batches):
            g, apart = b.column("g")[i].as_py(), np.setxor1d(lead, own, assume_unique=True)
            linked = (100 + c.percent) * len(apart) <= (100 - c.percent) * (len(own) + len(lead))
            strange = g != b.column("lead_g")[i].as_py()
            yield len(apart) + 64, b.column("a")[i].as_py(), b.column("b")[i].as_py(), g, strange and not linked, strange and linked, len(own), len(apart), b.column("sketch")[i].as_py(), apart.tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _batched(rows(batches), schema, 500_000)

    return run


def _pack(block: pa.Table) -> pa.Table:
    """The rows of one block as one row, each column's values behind one another."""
    block = block.sort_by("b")
    kinds = {"probe": bool}
    data = {x: [block.column(x).to_numpy().astype(kinds.get(x, np.int64)).tobytes()] for x in _BLOCK}
    data |= {x: [b"".join(block.column(x).to_pylist())] for x in ("sketch", "shingles")}
    one = {"a": [block.column("a")[0].as_py()], "block": [block.column("block")[0].as_py()], "asks": [any(block.column("probe").to_pylist())]}
    return pa.table({k: pa.array(v, {"asks": pa.bool_()}.get(k, pa.int64() if k in ("a", "block") else pa.binary())) for k, v in (one | data).items()})


class _Block:
    def __init__(self, row: dict, side: int, signature: int):
        read = lambda x, kind: np.frombuffer(row[f"{x}{side}"], kind)
        self.id, self.g, self.size, self.d = (read(x, np.int64) for x in ("b", "g", "size", "d"))
        self.probe, self.shingles, self.sketch = read("probe", bool), read("shingles", np.uint64), read("sketch", "<u2").reshape(-1, signature)
        self.at = np.concatenate(([0], np.cumsum(self.d)))

    def lists(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """The distinct shingles; where each one's list of rows starts and how long it is; the lists."""
        order = np.argsort(self.shingles, kind="stable")
        return *np.unique(self.shingles[order], return_index=True, return_counts=True), np.repeat(np.arange(len(self.d)), self.d)[order]


def compare_blocks(x: _Block, y: _Block, c: NearDupConfig) -> list[tuple[int, int]]:
    """Links from the probes of x to rows of y in other groups, as few as join all groups that such links join."""
    n = c.bands * c.rows
    least = [(k, least_matches(k, c.percent / 100, c.miss)) for k in range(c.batch, n + 1, c.batch)]
    known, start, length, owner = y.lists()
    root_x, root_y, out = x.g.copy(), y.g.copy(), []
    for i in np.flatnonzero(x.probe).tolist():
        alive = np.flatnonzero(root_y != root_x[i])
        matches, done = np.zeros(len(alive), np.int64), 0
        for k, m in least:
            matches += (y.sketch[alive, done:k] == x.sketch[i, done:k]).sum(axis=1)
            near = matches >= m
            alive, matches, done = alive[near], matches[near], k
        own = x.shingles[x.at[i] : x.at[i + 1]]
        if not len(alive) or not len(own) or not len(known):
            continue
        place = np.minimum(np.searchsorted(known, own), len(known) - 1)
        place = place[known[place] == own]
        many = length[place]
        ends = np.cumsum(many)
        rows = owner[np.arange(ends[-1]) - np.repeat(ends - many - start[place], many)] if len(ends) else owner[:0]
        common = np.bincount(rows, minlength=len(y.d))[alive]
        apart = x.d[i] + y.d[alive] - 2 * common
        for j in alive[(100 + c.percent) * apart <= (100 - c.percent) * (x.size[i] + y.size[alive])].tolist():
            if root_y[j] != root_x[i]:
                out.append((int(x.id[i]), int(y.id[j])))
                new, old = root_x[i], root_y[j]
                root_x[root_x == old], root_y[root_y == old] = new, new
    return out


def _compare(c: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                row = {x: b.column(x)[k].as_py() for x in b.schema.names}
                out = compare_blocks(*(_Block(row, side, c.bands * c.rows) for side in (1, 2)), c)
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], ["a", "b"])

    return run


class NearDuplicates:
    """One run over docs whose ids, where not null, do not repeat."""

    def __init__(self, docs: DataFrame, config: NearDupConfig, work: Work):
        self.c, self.docs, self.work = config, docs, work

    def result(self) -> DataFrame:
        c, work = self.c, self.work
        schema = "doc_id long, n_shingles long, key binary, sketch binary, bands array<long>"
        signed = work.table(self.docs.mapInArrow(_sign(c), schema), "signed")
        # equal word sequences have equal rows, so any row's signature stands for the class
        classes = signed.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("key").agg(F.min("doc_id").alias("id"), F.count("*").alias("n"), F.first("sketch").alias("sketch"), F.first("bands").alias("bands"))
        classes = work.table(classes, "classes")
        self.sketches = classes.select("id", F.col("sketch").alias("v"))
        rows = classes.select("id", F.explode("bands").alias("band"))
        sizes = work.table(rows.groupBy("band").agg(F.count("*").alias("n")).where("n > 1"), "sizes")
        held = work.table(spread_join(rows, sizes, ["band"]), "held")
        # a class in full buckets is near the middle of what is alike, and links more of it than another
        weight = held.groupBy("id").agg(F.sum("n").alias("weight"))
        leaders = held.join(weight, "id").groupBy("band").agg(F.first("n").alias("n"), F.min_by("id", F.struct(-F.col("weight"), "id")).alias("leader"))
        buckets = work.table(spread_join(held.drop("n"), work.table(leaders, "leaders"), ["band"]), "buckets")

        alike = work.table(self._pruned(buckets.where("id != leader").select(F.col("leader").alias("a"), F.col("id").alias("b")).distinct()), "alike")
        first = alike.groupBy("b").agg(F.min("a").alias("a"))
        links = work.table(self._confirmed(first), "links")
        groups = work.table(components(work, links.select(F.col("a").alias("u"), F.col("b").alias("v"))), "groups")

        rest = self._apart(alike.join(first, ["a", "b"], "left_anti"), groups)
        more = work.table(self._confirmed(rest).unionByName(self._among(buckets, groups)), "more")
        # from here on, groups stand for their members
        named = groups.withColumnRenamed("component", "g")
        ends = more.join(named.select(F.col("node").alias("a"), F.col("g").alias("ga")), "a", "left").join(named.select(F.col("node").alias("b"), F.col("g").alias("gb")), "b", "left")
        top = components(work, ends.select(F.coalesce("ga", "a").alias("u"), F.coalesce("gb", "b").alias("v"))).select(F.col("node").alias("g"), F.col("component").alias("t"))
        member = groups.select("node", F.col("component").alias("g")).unionByName(top.select(F.col("g").alias("node"), "g")).distinct()
        sizes = work.table(member.groupBy("g").agg(F.count("*").alias("n")).join(top, "g", "left").select("g", "n", "t"), "tops")
        final = spread_join(member, sizes, ["g"]).select(F.col("node").alias("id"), F.coalesce("t", "g").alias("component"))
        final = final.groupBy("id").agg(F.min("component").alias("component"))
        named = work.table(classes.select("key", "id", "n").join(final, "id", "left").select("key", "n", F.coalesce("component", "id").alias("component")), "named")
        out = spread_join(signed.select("doc_id", "n_shingles", "key"), named, ["key"], how="left")
        component = F.when(F.col("doc_id").isNotNull(), F.coalesce(F.when(F.col("n_shingles") > 0, F.col("component")), "doc_id"))
        return out.select("doc_id", "n_shingles", component.alias("component_id"), (component.eqNullSafe(F.col("doc_id"))).alias("kept"))

    def counts(self) -> DataFrame:
        """doc_id, n_shingles and a null component_id."""
        rows = self.docs.mapInArrow(_sign(self.c), "doc_id long, n_shingles long, key binary, sketch binary, bands array<long>")
        return rows.select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"))

    def _apart(self, pairs: DataFrame, groups: DataFrame) -> DataFrame:
        """Pairs (a, b) whose ends are in no common group yet."""
        ga, gb = groups.select(F.col("node").alias("a"), F.col("component").alias("ga")), groups.select(F.col("node").alias("b"), F.col("component").alias("gb"))
        return pairs.join(ga, "a", "left").join(gb, "b", "left").where("coalesce(ga, a) != coalesce(gb, b)").select("a", "b")

    def _beside(self, pairs: DataFrame, values: DataFrame, fans: DataFrame | None = None, more: tuple[str, ...] = ()) -> DataFrame:
        """The stream of pairs (a, b; a written table) in runs: a row of a with its value v (b null), then rows of its followers b with theirs.

        A leader's value moves once for every `beside` followers, so that followers of a hot leader spread over tasks.
        """
        fans = fans or self.work.table(pairs.groupBy("a").agg(F.count("*").alias("n")), "fans")
        runs = F.ceil(F.col("n") / self.c.beside).cast("int")
        dealt = spread_join(pairs, fans, ["a"]).select("a", F.pmod(F.xxhash64("b"), runs).cast("int").alias("run"), "b", *more)
        follow = dealt.join(values.withColumnRenamed("id", "b"), "b").select("a", "run", "b", *more, "v")
        none = [F.lit(None).cast(dealt.schema[x].dataType).alias(x) for x in ("b", *more)]
        lead = fans.select("a", F.explode(F.sequence(F.lit(0), runs - 1)).alias("run")).join(values.withColumnRenamed("id", "a"), "a").select("a", "run", *none, "v")
        return lead.unionByName(follow).repartition("a", "run").sortWithinPartitions("a", "run", F.col("b").asc_nulls_first()).drop("run")

    def _texts(self, pairs: DataFrame) -> DataFrame:
        """id, v: the texts of the ends of pairs, a written table."""
        ids = self.work.table(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), "ids")
        return semi_join(self.docs, ids, "doc_id").select(F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).alias("v"))

    def _pruned(self, pairs: DataFrame) -> DataFrame:
        return self._beside(self.work.table(pairs, "pairs"), self.sketches).mapInArrow(_prune(self.c), "a long, b long")

    def _confirmed(self, pairs: DataFrame) -> DataFrame:
        pairs = self.work.table(pairs, "pairs")
        return self._beside(pairs, self._texts(pairs)).mapInArrow(_confirm(self.c), "a long, b long")

    def _among(self, buckets: DataFrame, groups: DataFrame) -> DataFrame:
        """Links among the followers of one leader that stay in several groups, and with their leader."""
        c, work = self.c, self.work
        named = groups.select(F.col("node").alias("id"), F.col("component").alias("g"))
        placed = work.table(buckets.where("n > 2").join(named, "id", "left").select("band", "id", "leader", "n", F.coalesce("g", "id").alias("g")), "placed")
        split = placed.groupBy("band").agg(F.min("g").alias("low"), F.max("g").alias("high"), F.first("n").alias("n")).where("low != high").select("band", "n")
        split = spread_join(placed.drop("n"), work.table(split, "split"), ["band"])
        stars = work.table(split.where("id != leader").select(F.col("leader").alias("a"), F.col("id").alias("b"), "g").distinct(), "stars")
        fans = stars.groupBy("a").agg(F.count("*").alias("n")).join(named.select(F.col("id").alias("a"), F.col("g").alias("lead_g")), "a", "left").select("a", "n", F.coalesce("lead_g", "a").alias("lead_g"))
        fans = work.table(fans, "fans")
        followers = spread_join(stars, fans, ["a"]).drop("n").join(self.sketches.toDF("b", "sketch"), "b").select("a", "b", "g", "lead_g", "sketch")
        stream = self._beside(work.table(followers, "followers"), self._texts(stars), fans.drop("lead_g"), ("g", "lead_g", "sketch"))
        apart = work.table(stream.mapInArrow(_differ(c), _DIFFERENCES), "apart")
        cells = apart.groupBy("a").agg(F.ceil(F.greatest(F.sum("d"), F.count("*")) / c.block).alias("blocks"), F.count("*").alias("n"), F.max("probe").alias("asks")).where("asks").select("a", "blocks", "n")
        cells = work.table(cells, "cells")
        dealt = spread_join(apart.where("NOT linked"), cells, ["a"]).withColumn("block", F.pmod(F.xxhash64("b"), "blocks"))
        packed = work.table(dealt.select("a", "block", *_BLOCK, "sketch", "shingles").groupBy("a", "block").applyInArrow(_pack, _BLOCKS), "blocks")
        # names of blocks first: a block's data go once to each block that it meets
        pairs = packed.where("asks").select("a", F.col("block").alias("block1")).join(packed.select("a", F.col("block").alias("block2")), "a")
        side = lambda k: packed.select("a", *[F.col(x).alias(f"{x}{k}") for x in packed.columns if x not in ("a", "asks")])
        both = pairs.join(side(1), ["a", "block1"]).join(side(2), ["a", "block2"])
        names = [f"{x}{k}" for k in (1, 2) for x in (*_BLOCK, "sketch", "shingles")]
        links = both.select(*names).mapInArrow(_compare(c), "a long, b long")
        return links.unionByName(apart.where("linked").select("a", "b"))


def _unique(docs: DataFrame, work: Work) -> tuple[DataFrame, DataFrame | None]:
    """docs (doc_id, text), and None; or, where ids repeat, a written copy whose `row` numbers the rows."""
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"))
    if ids.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").isEmpty():
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), None
    rows = work.table(docs.select("*", F.monotonically_increasing_id().alias(_ROW)), "rows")
    own = F.when(F.col("doc_id").isNotNull(), F.col(_ROW))
    return rows.select(own.alias("doc_id"), "text"), rows


_ROW = "near_duplicates_row_number"


def near_duplicates(docs: DataFrame, config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links), kept, for every row of docs (doc_id, text; other columns are ignored).

    Texts that are null, empty or without words have no shingles and are their own component. Rows with a null doc_id
    keep their shingle count, link with nothing, get a null component_id and are kept. Repeated rows each get a row; rows
    that share a doc_id and not the text each follow their own text's links. An empty table gives an empty one.
    Writes signatures, buckets, pairs and links to the work folder; nothing grows on the driver.
    """
    work = Work(docs.sparkSession)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    unique, rows = _unique(own, work)
    out = NearDuplicates(unique, config, work).result()
    if rows is None:
        return out
    out = work.table(rows.select("doc_id", F.col(_ROW).alias("row")).join(out.where("doc_id IS NOT NULL").select(F.col("doc_id").alias("row"), "n_shingles", F.col("component_id").alias("c")), "row", "left"), "by_row")
    least = work.table(out.where("n_shingles > 0").groupBy("c").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")), "least")
    known = spread_join(out.where("n_shingles > 0"), least, ["c"]).select("doc_id", "n_shingles", F.col("least").alias("component_id"))
    alone = out.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    nameless = NearDuplicates(own.where("doc_id IS NULL"), config, work).counts()
    return known.unionByName(alone).unionByName(nameless).withColumn("kept", F.col("component_id").eqNullSafe(F.col("doc_id")))


def deduplicated(docs: DataFrame, config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """One row of docs for each group of near duplicates, one with its smallest doc_id, all columns kept.

    Rows without words or with a null doc_id are in no group and stay. Each row follows its own text: of rows that repeat
    an id, one with another text stays if nothing is like it, and of rows that repeat a text one stays. An empty table
    gives an empty one. Ids of dropped documents are broadcast where they are few, so that texts need no shuffle.
    """
    work = Work(docs.sparkSession)
    unique, rows = _unique(docs, work)
    out = NearDuplicates(unique, config, work).result()
    if rows is None:
        gone = work.table(out.where("NOT kept").select("doc_id").distinct(), "gone")
        return semi_join(docs, gone, "doc_id", anti=True).select(*docs.columns)
    groups = out.where("n_shingles > 0 AND doc_id IS NOT NULL").select(F.col("doc_id").alias(_ROW), "component_id")
    named = work.table(rows.select(_ROW, F.col("doc_id").cast("long").alias("id")).join(groups, _ROW), "named")
    best = work.table(named.groupBy("component_id").agg(F.min(F.struct("id", _ROW))[_ROW].alias("best"), F.count("*").alias("n")), "best")
    gone = work.table(spread_join(named, best, ["component_id"]).where(F.col(_ROW) != F.col("best")).select(_ROW), "gone")
    return semi_join(rows, gone, _ROW, anti=True).select(*docs.columns)

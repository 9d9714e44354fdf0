"""Exact Jaccard self-join of shingle sets, small sets by subsets, large sets by inverted lists.

A document's set holds its distinct 4-word shingles (its whole word sequence if it has fewer words). Equal sets are one
node from the start. Two sets of s and t shingles link when 100 * both >= 85 * either, that is when they share at least
need(s, t) shingles.

Small sets (up to a boundary): each one enumerates, for every partner size t, its subsets of need(s, t) shingles. Two sets
that agree on one are linked, whatever else they hold, so a group of any size needs a star and no pairs. Large sets are
put into inverted lists by the shingles of their prefix, rarest first, so that linked sets meet in a list, and common
passages stay out of the prefixes; a list first tries its most central member against the others, and only members that
are still in different components afterwards are paired. The boundary is where the summed cost of both ways, from the
count of sets of each size, is least.

The order by rarity uses shingles found often within an Arrow batch, at most `heavy_max` of them, counted over all
documents; any fixed order gives the same, exact, result, so this bound costs no links. Every candidate is verified on
full sets of 64-bit shingle hashes.

Defined cases: null, empty and wordless texts have 0 shingles and link with nothing; rows that share a doc_id are one
node; rows without doc_id get a null component and link with nothing; repeated texts are copies; an empty table gives
no rows. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.llm.common import components, discard, materialize, of_type, sliced


@dataclass(frozen=True)
class JaccardParams:
    shingle: int = 4
    percent: int = 85
    heavy_max: int = 1 << 17
    heavy_in_batch: int = 4
    largest_boundary: int = 24
    #: In subset keys, which are counted and joined: a posting is shuffled, sorted and joined, and brings whole sets to compare.
    posting_cost: float = 6.0


PRODUCTION = JaccardParams()
#: Texts that are cut into words together.
SLICE = 250
#: Bits of the map that keeps texts of no candidate from being cut into shingles again: 8 MB.
BITS = 1 << 26
#: Members of a key that are paired in one part.
SALT = 512
_MUL = np.uint64(0x9E3779B97F4A7C15)


def need(s: int, t: int, percent: int = 85) -> int:
    """Least overlap at which sets of s and t elements link."""
    return -(-percent * (s + t) // (100 + percent))


def need_column(s: Column, t: Column, percent: int) -> Column:
    return F.floor(((s + t) * percent + (99 + percent)) / F.lit(100 + percent)).cast("long")


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xC2B2AE3D27D4EB4F)
    return x ^ (x >> np.uint64(32))


class Shingler:
    """Sets of a batch of texts, some at a time; each different word among them is hashed once."""

    def __init__(self, width: int):
        self.width = width

    def sets(self, texts: list[str | None]) -> list[np.ndarray]:
        return [s for k in range(0, len(texts), SLICE) for s in self._slice(texts[k : k + SLICE])]

    def _slice(self, texts: list[str | None]) -> list[np.ndarray]:
        class Seen(dict):
            def __missing__(self, word: bytes) -> int:
                self[word] = k = len(self)
                return k

        seen = Seen()
        look = seen.__getitem__
        rows = [t.encode("utf-8", "surrogatepass").lower().split() if t else [] for t in texts]
        sizes = np.fromiter(map(len, rows), np.int64, len(rows))
        codes = np.fromiter((look(w) for row in rows for w in row), np.int64, int(sizes.sum()))
        hashes = mix(np.fromiter((xxhash.xxh3_64_intdigest(w) for w in seen), np.uint64, len(seen)))
        words, starts = hashes[codes] if len(codes) else np.zeros(0, np.uint64), np.cumsum(sizes) - sizes
        # windows over all texts at once; those that reach into the next text are never read
        n, acc = len(words), np.full(len(words), self.width, np.uint64)
        for k in range(self.width):
            acc[: n - k] = (acc[: n - k] ^ (acc[: n - k] >> np.uint64(31))) * _MUL + words[k:]
        acc = mix(acc)
        out = []
        for start, size in zip(starts.tolist(), sizes.tolist()):
            if size >= self.width:
                out.append(np.unique(acc[start : start + size - self.width + 1]))
            elif size:
                whole = np.full(1, size, np.uint64)
                for k in range(start, start + size):
                    whole = (whole ^ (whole >> np.uint64(31))) * _MUL + words[k : k + 1]
                out.append(mix(whole))
            else:
                out.append(np.zeros(0, np.uint64))
        return out


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def shingle_sets(docs: DataFrame, p: JaccardParams) -> DataFrame:
    """doc_id, n, sig (128 bits of the whole set); and a row of n = -1 per Arrow batch: the shingles that the batch holds often."""
    names = ["doc_id", "n", "sig", "heavy", "times"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = lambda n: pa.nulls(n, pa.list_(pa.int64()))
        for batch in batches:
            every = []
            for part in sliced([batch]):
                sets = Shingler(p.shingle).sets(part.column("text").to_pylist())
                sigs = pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), sigs, none(len(sets)), none(len(sets))], names)
                every.append(np.concatenate(sets))
            values = np.concatenate(every) if every else np.zeros(0, np.uint64)
            del every
            values.sort()
            starts = np.flatnonzero(np.concatenate([np.ones(min(1, len(values)), bool), values[1:] != values[:-1]]))
            counts = np.diff(np.append(starts, len(values)))
            often = counts >= p.heavy_in_batch
            found = [pa.array([x.tolist()], pa.list_(pa.int64())) for x in (_signed(values[starts[often]]), counts[often])]
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.array([-1], pa.int64()), pa.nulls(1, pa.binary()), *found], names)

    return docs.mapInArrow(run, "doc_id long, n long, sig binary, heavy array<long>, times array<long>")


def sets_in(column: pa.Array) -> list[np.ndarray]:
    """Stored sets: ascending hashes, end to end."""
    return [np.frombuffer(x, np.uint64) for x in column.to_pylist()]


def boundary(sizes: dict[int, int], p: JaccardParams) -> int:
    """The size up to which enumerating subsets costs least in all."""
    def subsets(s: int) -> int:
        return sum(comb(s, need(s, t, p.percent)) for t in partners(s, p.percent))

    def postings(s: int) -> float:
        return p.posting_cost * prefix_length(s, p.percent)

    def total(b: int) -> float:
        return sum(n * subsets(s) for s, n in sizes.items() if 0 < s <= b) + sum(n * postings(s) for s, n in sizes.items() if s >= least_partner(b + 1, p.percent))

    return min(range(1, p.largest_boundary + 1), key=total)


def least_partner(s: int, percent: int) -> int:
    return -(-percent * s // 100)


def partners(s: int, percent: int) -> list[int]:
    return [t for t in range(least_partner(s, percent), 100 * s // percent + 1) if need(s, t, percent) <= min(s, t)]


def prefix_length(s: int, percent: int) -> int:
    return s - least_partner(s, percent) + 1


@lru_cache(maxsize=64)
def _choices(n: int, k: int) -> np.ndarray:
    """All k-subsets of n places, as rows of a 0/1 matrix."""
    picks = np.array(list(combinations(range(n), k)), np.int64).reshape(-1, k)
    out = np.zeros((len(picks), n), np.uint64)
    np.put_along_axis(out, picks, np.uint64(1), axis=1)
    return out


def subset_keys(values: np.ndarray, percent: int) -> list[tuple[int, int, int]]:
    """(smaller size, larger size, subset hash) for each partner size and subset."""
    s, spread, out = len(values), mix(values * _MUL), []
    for t in partners(s, percent):
        hashes = mix(_choices(s, need(s, t, percent)) @ spread)
        out += [(min(s, t), max(s, t), h) for h in _signed(hashes).tolist()]
    return out


def signatures(docs: DataFrame, heavy, bound: int, p: JaccardParams) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n, prefix (shingle hashes, rarest first), common (which of them are heavy), subsets."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, rank = heavy.value
        for batch in sliced(batches):
            sets = Shingler(p.shingle).sets(batch.column("text").to_pylist())
            prefix, common, subsets = [], [], []
            for s in sets:
                n = len(s)
                if n and n >= least_partner(bound + 1, p.percent):
                    at = np.searchsorted(known, s)
                    at[at == len(known)] = 0
                    is_heavy = known[at] == s if len(known) else np.zeros(n, bool)
                    k = prefix_length(n, p.percent)
                    light = s[~is_heavy]  # ascending hashes: a fixed order
                    if len(light) >= k:
                        chosen, flags = light[:k], np.zeros(k, bool)
                    else:
                        more = s[is_heavy][np.argsort(rank[at[is_heavy]], kind="stable")][: k - len(light)]
                        chosen, flags = np.concatenate([light, more]), np.arange(k) >= len(light)
                    prefix.append(_signed(chosen))
                    common.append(flags)
                else:
                    prefix.append(None)
                    common.append(None)
                subsets.append([{"lo": a, "hi": b, "key": c} for a, b, c in subset_keys(s, p.percent)] if 0 < n <= bound else None)
            kind = pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64()), ("key", pa.int64())]))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(prefix, pa.list_(pa.int64())), pa.array(common, pa.list_(pa.bool_())), pa.array(subsets, kind)],
                ["doc_id", "n", "prefix", "common", "subsets"],
            )

    return docs.mapInArrow(run, "doc_id long, n long, prefix array<long>, common array<boolean>, subsets array<struct<lo:long,hi:long,key:long>>")


def small_edges(subsets: DataFrame) -> DataFrame:
    """doc_id, n, lo, hi, key -> star edges: all who share a key are linked through its smallest members."""
    by = subsets.groupBy("lo", "hi", "key").agg(
        F.min(F.when(F.col("n") == F.col("lo"), F.col("doc_id"))).alias("a"), F.min(F.when(F.col("n") == F.col("hi"), F.col("doc_id"))).alias("b"), F.count("*").alias("m")
    )
    centres = by.where("m > 1 AND a IS NOT NULL AND b IS NOT NULL")
    other = F.when(F.col("n") == F.col("lo"), F.col("b")).otherwise(F.col("a"))
    return subsets.join(centres, ["lo", "hi", "key"]).select("doc_id", other.alias("other")).where("doc_id <> other").distinct()


def _possible(n1: Column, p1: Column, n2: Column, p2: Column, percent: int) -> Column:
    """Sizes can link, and what follows the first common shingle can still hold enough."""
    least = need_column(n1, n2, percent)
    return (least <= F.least(n1, n2)) & (least <= 1 + F.least(n1 - p1, n2 - p2) - 1)


def among(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """docs whose doc_id is in ids, and a few others: a bitmap of hashed ids goes to every task, the texts stay where they are.

    The bitmap has BITS bits at most, whatever the number of ids; when it fills up, more texts pass and none is lost.
    """
    place = (F.pmod(F.xxhash64("doc_id"), F.lit(BITS)) + 1).cast("long")
    marks = ids.select(F.bitmap_bucket_number(place).alias("_bucket"), F.bitmap_bit_position(place).alias("_bit"))
    bitmap = marks.groupBy("_bucket").agg(F.bitmap_construct_agg("_bit").alias("_bits"))
    at = F.bitmap_bit_position(place).cast("int")
    byte = F.conv(F.hex(F.substring("_bits", F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = docs.withColumn("_bucket", F.bitmap_bucket_number(place)).join(F.broadcast(bitmap), "_bucket")
    return hit.where(F.call_function("shiftright", byte, at % 8).bitwiseAND(F.lit(1)) == 1).select(*docs.columns)


def plausible(pairs: DataFrame, docs: DataFrame, p: JaccardParams) -> DataFrame:
    """pairs(a, b) without those that cannot link, by 16 bits of each shingle.

    Common shingles have common marks, and a set has as many shingles more than marks as it repeats marks; so common marks
    plus the smaller of these surpluses bound the overlap from above, and no link is lost.
    """
    ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            sets = Shingler(p.shingle).sets(batch.column("text").to_pylist())
            marks = [np.unique((s >> np.uint64(48)).astype(np.uint16)).view(np.int16) for s in sets]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(s) for s in sets], pa.int32()), pa.array(marks, pa.list_(pa.int16()))], ["doc_id", "n", "marks"])

    marked = materialize(among(docs, ids).mapInArrow(run, "doc_id long, n int, marks array<short>"), "marks")
    left = marked.select(F.col("doc_id").alias("a"), F.col("n").alias("n1"), F.col("marks").alias("x"))
    right = marked.select(F.col("doc_id").alias("b"), F.col("n").alias("n2"), F.col("marks").alias("y"))
    most = F.size(F.array_intersect("x", "y")) + F.least(F.col("n1") - F.size("x"), F.col("n2") - F.size("y"))
    full = pairs.hint("merge").join(left, "a").hint("merge").join(right, "b").withColumn("_most", most)
    out = materialize(full.where(F.col("_most") * 100 >= (F.col("n1") + F.col("n2") - F.col("_most")) * p.percent).select("a", "b").distinct(), "pairs")
    discard(marked)
    return out


def linking(pairs: DataFrame, docs: DataFrame, p: JaccardParams, tag: str) -> DataFrame:
    """pairs(a, b) -> those that link, by their full sets."""
    all_ = materialize(pairs, "open-pairs")
    pairs = plausible(all_, docs, p)
    ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            sets = Shingler(p.shingle).sets(batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([s.tobytes() for s in sets], pa.binary())], ["doc_id", "elements"])

    sets = materialize(among(docs, ids).mapInArrow(cut, "doc_id long, elements binary"), "sets")
    left = sets.select(F.col("doc_id").alias("a"), F.col("elements").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("elements").alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            both = zip(sets_in(batch.column("x")), sets_in(batch.column("y")))
            shared = [(len(np.intersect1d(x, y, assume_unique=True)), len(x) + len(y)) for x, y in both]
            keep = [100 * n >= p.percent * (total - n) for n, total in shared]
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    full = pairs.hint("merge").join(left, "a").hint("merge").join(right, "b").select("a", "b", "x", "y")
    links = materialize(full.mapInArrow(run, "a long, b long").distinct(), tag)
    discard(all_, pairs, sets)
    return links


def salted_pairs(members: DataFrame, key: list[str], fits: Column) -> DataFrame:
    """Every pair (a, b) of members of one key that fits(x, y); a key's left side is dealt over as many parts as it has SALTs of members."""
    parts = members.groupBy(*key).agg(F.count("*").alias("m")).where("m > 1").select(*key, F.ceil(F.col("m") / SALT).cast("int").alias("parts"))
    dealt = materialize(members.join(parts, key), "dealt")
    x = dealt.withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")).cast("int")).alias("x")
    y = dealt.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).alias("y")
    same = F.col("x.doc_id") != F.col("y.doc_id")
    for c in [*key, "part"]:
        same = same & (F.col(f"x.{c}") == F.col(f"y.{c}"))
    ends = F.least("x.doc_id", "y.doc_id").alias("a"), F.greatest("x.doc_id", "y.doc_id").alias("b")
    return x.join(y, same & fits).select(*ends).distinct()


def banded_pairs(members: DataFrame, p: JaccardParams, fits: Column) -> DataFrame:
    """salted_pairs by list and size: sets that link lie in the same band of sizes or in neighbouring ones, and a band is
    a little wider than the ratio of sizes that can link."""
    band = F.floor(F.log(F.col("n")) / float(np.log(100 / p.percent) * (1 + 1e-9))).cast("int")
    sized = members.withColumn("band", band)
    # each pair in the upper of its two bands: a set stands in its own band and in the next one
    return salted_pairs(sized.withColumn("at_band", F.explode(F.array("band", F.col("band") + 1))), ["h", "at_band"], fits & ((F.col("x.band") == F.col("x.at_band")) | (F.col("y.band") == F.col("x.at_band"))))


def jaccard_components(docs: DataFrame, p: JaccardParams = PRODUCTION, every_link: bool = False) -> DataFrame:
    """documents -> doc_id, n_shingles, component_id (smallest doc_id reachable).

    With `every_link` all candidate pairs of different sets are verified, also within a component, and n_links is how many
    other sets link with the document's own; copies are one set. Without it only what the components need is verified.
    """
    return _joined(docs, p, every_link)[0]


def jaccard_links(docs: DataFrame, p: JaccardParams = PRODUCTION) -> DataFrame:
    """documents -> a, b (a < b): every link between different sets, each set named by its smallest doc_id."""
    return _joined(docs, p, True)[1]


def _joined(docs: DataFrame, p: JaccardParams, every_link: bool) -> tuple[DataFrame, DataFrame]:
    spark = docs.sparkSession
    rows = of_type(docs, {"doc_id": "long", "text": "string"})
    sets = materialize(shingle_sets(rows, p), "shingles")
    often = sets.where("heavy IS NOT NULL").select(F.explode(F.arrays_zip("heavy", "times")).alias("x")).select("x.heavy", "x.times")
    top = often.groupBy("heavy").agg(F.sum("times").alias("times")).orderBy(F.col("times").desc(), "heavy").limit(p.heavy_max).toArrow()  # at most heavy_max
    known, times = top.column("heavy").to_numpy().view(np.uint64), top.column("times").to_numpy()
    order = np.argsort(known)
    heavy = spark.sparkContext.broadcast((known[order], times[order]))
    # copies: one node per set; rows of one doc_id are one node too
    real = sets.where("doc_id IS NOT NULL AND n > 0").select("doc_id", "n", "sig")
    copies = real.groupBy("sig").agg(F.min("doc_id").alias("rep"), F.any_value("n").alias("n"))
    nodes = materialize(real.join(copies.select("sig", "rep"), "sig").select("doc_id", "rep").distinct(), "nodes")
    sizes = {r["n"]: r["m"] for r in copies.groupBy("n").agg(F.count("*").alias("m")).collect()}  # one number per size
    bound = boundary(sizes, p)

    reps = nodes.where("doc_id = rep").select("doc_id")
    texts = rows.where("doc_id IS NOT NULL")
    signed = materialize(signatures(texts, heavy, bound, p).where("n > 0").join(reps.hint("merge"), "doc_id", "left_semi"), "signatures")
    few = signed.where("subsets IS NOT NULL").select("doc_id", "n", F.explode("subsets").alias("s")).select("doc_id", "n", "s.*").distinct()
    by_subset = small_edges(few).select(F.col("doc_id").alias("a"), F.col("other").alias("b"))

    postings = signed.where("prefix IS NOT NULL").select("doc_id", F.col("n").cast("int").alias("n"), F.posexplode(F.arrays_zip("prefix", "common")).alias("at", "e"))
    postings = postings.select("doc_id", "n", "at", F.col("e.prefix").alias("h"), F.col("e.common").alias("common"))
    every = Window.partitionBy("h").orderBy("at", "doc_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    member = F.struct("at", "doc_id", "n")
    rare = postings.where("NOT common").withColumn("m", F.count("*").over(every)).withColumn("c", F.first(member).over(every)).where("m > 1")
    # lists of heavy shingles may be long: combined before the shuffle, and their join can be split
    common = postings.where("common")
    centres = common.groupBy("h").agg(F.count("*").alias("m"), F.min(member).alias("c")).where("m > 1")
    lists = materialize(rare.unionByName(common.join(centres, "h")).select("h", "at", "doc_id", "n", "c"), "lists")

    if every_link:
        x_n, y_n = F.col("x.n"), F.col("y.n")
        larger = _possible(x_n, F.col("x.at"), y_n, F.col("y.at"), p.percent) & (F.greatest(x_n, y_n) > bound)
        pairs = banded_pairs(lists.select("h", "at", "doc_id", "n"), p, larger)
        smaller = (F.least(x_n, y_n) == F.col("x.lo")) & (F.greatest(x_n, y_n) == F.col("x.hi"))
        pairs = pairs.union(salted_pairs(few, ["lo", "hi", "key"], smaller)).distinct()
        links = linking(pairs, texts, p, "every-link")
        copied = nodes.where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
        return _labelled(sets, nodes, links, copied, every_link), links

    tried = lists.where(F.col("doc_id") != F.col("c.doc_id")).where(_possible(F.col("n"), F.col("at"), F.col("c.n"), F.col("c.at"), p.percent))
    tried = tried.select(F.least("doc_id", "c.doc_id").alias("a"), F.greatest("doc_id", "c.doc_id").alias("b")).distinct()
    tried = materialize(tried.union(by_subset.select(F.least("a", "b"), F.greatest("a", "b"))).distinct(), "stars")
    discard(signed)
    first = linking(tried, texts, p, "star-links")
    copied = nodes.where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    group = components(first)

    # what is still apart within a list; sets of at most `bound` on both sides are settled by their subsets
    of = group.select(F.col("node").alias("doc_id"), "component")
    split = lists.select("h", "at", "doc_id", "n").join(of, "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    open_ = split.groupBy("h").agg(F.min("component").alias("_lo"), F.max("component").alias("_hi")).where("_lo <> _hi").select("h")
    rest = split.join(open_, "h", "left_semi")
    fits = (F.col("x.component") != F.col("y.component")) & _possible(F.col("x.n"), F.col("x.at"), F.col("y.n"), F.col("y.at"), p.percent) & (F.greatest("x.n", "y.n") > bound)
    more = banded_pairs(rest, p, fits).join(tried, ["a", "b"], "left_anti")
    second = linking(more, texts, p, "more-links")

    links = first.union(second).distinct()
    return _labelled(sets, nodes, links, copied, every_link), links


def _labelled(sets: DataFrame, nodes: DataFrame, links: DataFrame, copied: DataFrame, every_link: bool) -> DataFrame:
    whole = components(links.union(copied)).select(F.col("node").alias("doc_id"), "component")
    out = sets.where("n >= 0").select("doc_id", F.col("n").alias("n_shingles")).join(whole, "doc_id", "left")
    columns = ["doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id")]
    if every_link:
        both = links.select(F.col("a").alias("rep"), F.col("b").alias("other")).union(links.select("b", "a"))
        degree = nodes.join(both, "rep").groupBy("doc_id").agg(F.countDistinct("other").alias("n_links"))
        out = out.join(degree, "doc_id", "left")
        columns.append(F.coalesce("n_links", F.lit(0)).alias("n_links"))
    return out.select(*columns)


def without_near_copies(docs: DataFrame, p: JaccardParams = PRODUCTION) -> DataFrame:
    """docs with one document of each component: the one with the smallest doc_id (rows without doc_id all stay)."""
    found = jaccard_components(docs, p).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(found, "doc_id", "left_anti").select(*docs.columns)


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "n_shingles", "component_id")


ORACLE = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents
), s AS (
  SELECT DISTINCT doc_id, array_to_string(words[CAST(i AS INTEGER) : CAST(i AS INTEGER) + 3], ' ') AS shingle
  FROM (SELECT doc_id, words, unnest(range(1, greatest(len(words) - 3, least(len(words), 1)) + 1)) AS i FROM w)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
l AS (
  SELECT x.a, x.b FROM (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS shared FROM s p JOIN s q ON p.shingle = q.shingle AND p.doc_id <> q.doc_id GROUP BY ALL) x
  JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * shared >= 85 * (na.n + nb.n - shared)
), reach AS (
  SELECT doc_id, doc_id AS other FROM documents UNION SELECT reach.doc_id, l.b FROM reach JOIN l ON l.a = reach.other
)
SELECT d.doc_id, CAST(coalesce(any_value(n.n), 0) AS BIGINT) AS n_shingles, min(other) AS component_id
FROM documents d JOIN reach ON reach.doc_id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id GROUP BY d.doc_id
"""

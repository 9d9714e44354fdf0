"""Line deduplication by a segment-partition edit join, in DataFrame functions only.

A line is removed if an earlier line (by doc_id, then line number) is near it. Two lines are near if they are equal, or if
they differ by at most one edit for each `chars_per_edit` characters of the shorter one, and by `edits` at most: lines of
less than `chars_per_edit` characters must be equal. Equal lines meet by one 128-bit key a line, the others in an edit join
of the different lines: a line is cut into one segment more than its edits, of which a longer or equally long partner must
contain one unchanged; per partner length and segment only the few substrings at places that can matter are probed (bounds
from both ends of the line). Candidates lose their common ends, and a bit-parallel distance over a band of 2 * edits + 1
diagonals, one 64-bit word a column, decides.

Lines are combined by key before anything is joined; texts are fetched again for candidates only. One earlier partner is all
that a line needs, so a key with many lines first tries all of them against its earliest ones, which is linear, and only
lines that are still there are compared with all earlier lines of the key. A family of lines near its first one so costs as
many candidates as it has lines; the worst case is a family of n lines that share a segment and are mostly not near each
other, where n * n / 2 counts of letters are compared, dealt over parts.

Defined cases: lines without a non-space character are never removed; null and empty texts have no lines; rows without
doc_id take no part and keep their text; rows that repeat a doc_id are one document; lines longer than any bound are
joined whole; an empty table gives no rows. Extra columns pass through.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.llm.common import materialize, of_type


@dataclass(frozen=True)
class LineParams:
    edits: int = 2
    chars_per_edit: int = 12


PRODUCTION = LineParams()
#: Characters whose counts are compared, from how many possible pairs of one key on it is tried by its earliest lines first,
#: how many lines of a key are compared in one part, and how many keys may be sent to every task (8 MB).
LETTERS = "abcdefghijklmnopqrstuvwxyz0123456789"
LONG_LIST = 64
PART = 4096
MAX_SENT = 1 << 20


def with_keys(lines: DataFrame, p: LineParams) -> tuple[DataFrame, list[int]]:
    """lines(line, len, ...) -> with `keys`, and the places of those that the line itself is listed under.

    A line probes, for each length that a partner as long or shorter may have, that partner's segments at the places where
    they can lie in it; its own length without a shift gives the keys of its own segments. A length that is allowed fewer
    edits has fewer segments, and its places are among those of the most edits; what it does not need is null.
    """
    k = p.edits + 1
    for d in range(k):
        length = F.col("len") - d
        lines = lines.withColumn(f"_l{d}", length).withColumn(f"_k{d}", F.when(length >= p.chars_per_edit, allowed(length, p) + 1).otherwise(0))
    for d in range(k):
        parts = F.greatest(f"_k{d}", F.lit(1))
        lines = lines.withColumn(f"_b{d}", F.expr(f"_l{d} div greatest(_k{d}, 1)").cast("int")).withColumn(f"_e{d}", parts - F.col(f"_l{d}") % parts)
    for d in range(k):
        for i in range(k):
            begin = F.col(f"_b{d}") * i + F.greatest(F.lit(0), F.lit(i) - F.col(f"_e{d}")) + 1
            size = F.col(f"_b{d}") + F.when(F.col(f"_e{d}") <= i, 1).otherwise(0)
            lines = lines.withColumn(f"_s{d}_{i}", begin).withColumn(f"_n{d}_{i}", size)
    keys, own = [], []
    for d in range(k):
        for i in range(k):
            for shift in range(max(-i, d - (p.edits - i)), min(i, d + (p.edits - i)) + 1):
                if d == shift == 0:
                    own.append(len(keys))
                piece = F.substring(F.col("line"), F.col(f"_s{d}_{i}") + shift, F.col(f"_n{d}_{i}"))
                keys.append(F.when(F.col(f"_k{d}") > i, F.xxhash64(f"_l{d}", F.lit(i), piece)))
    names = [c for c in lines.columns if not c.startswith("_")]
    return lines.select(*names, F.array(*keys).alias("keys")), own


def allowed(shorter: Column, p: LineParams) -> Column:
    """Edits that a pair may differ by, from the length of its shorter line."""
    return F.least(F.lit(p.edits), F.floor(shorter / F.lit(p.chars_per_edit)).cast("int"))


def lines_of(docs: DataFrame) -> DataFrame:
    """doc_id, line_no, line: lines with a character other than white space."""
    rows = docs.where("doc_id IS NOT NULL AND text IS NOT NULL")
    return rows.select("doc_id", F.posexplode(F.split("text", "\n")).alias("line_no", "line")).where(F.col("line").rlike(r"[^\s]"))


def common_prefix(a: Column, b: Column) -> Column:
    """Length of the common prefix: halving steps, each one comparison of substrings."""
    steps = F.array(*[F.lit(1 << k) for k in range(30, -1, -1)])
    shorter = F.least(F.length(a), F.length(b))
    return F.aggregate(
        steps, F.lit(0), lambda n, k: F.when((n + k <= shorter) & (F.substring(a, n + 1, k) == F.substring(b, n + 1, k)), n + k).otherwise(n)
    )


def _let(value: Column, body) -> Column:
    """body(value), with value computed once."""
    return F.transform(F.array(value), body)[0]


def banded_distance(long_: Column, short: Column, edits: int) -> Column:
    """Edit distance of arrays of characters if it is at most `edits`, else some larger number.

    Needs 0 <= size(long_) - size(short) <= edits. Bit k of a word stands for row j - edits + k of column j; the words hold
    where the distance grows or falls down a column, and the sum follows the diagonal that ends in the last cell.
    """
    width = 2 * edits + 1
    mask = (1 << width) - 1
    m, n = F.size(long_), F.size(short)
    diagonal = m - n + edits
    word = lambda x: F.lit(x).cast("long")
    both = lambda x, y: x.bitwiseAND(y)
    either = lambda x, y: x.bitwiseOR(y)
    flip = lambda x: x.bitwiseXOR(word(mask))

    def matches(j: Column) -> Column:
        c = F.get(short, j - 1)
        bits = [F.when(F.get(long_, j - 1 - edits + k) == c, word(1 << k)).otherwise(word(0)) for k in range(width)]
        total = bits[0]
        for b in bits[1:]:
            total = total + b
        return total

    def step(s: Column, j: Column) -> Column:
        up, down = s["up"], s["down"]

        def with_match(x: Column) -> Column:
            diag = both(either(either((both(x, up) + up).bitwiseXOR(up), x), down), word(mask))
            return _let(diag, with_diag)

        def with_diag(d: Column) -> Column:
            right = both(either(down, flip(both(either(d, up), word(mask)))), word(mask))
            return _let(right, lambda h: after(d, h))

        def after(d: Column, h: Column) -> Column:
            next_d = F.shiftrightunsigned(d, 1)
            grown = both(either(both(d, up), flip(both(either(next_d, h), word(mask)))), word(mask))
            on = F.when(both(F.call_function("shiftrightunsigned", d, diagonal), word(1)) == 1, F.lit(0)).otherwise(F.lit(1))
            return F.struct(grown.alias("up"), both(next_d, h).alias("down"), (s["sum"] + on).alias("sum"))

        return F.when(s["sum"] > edits, s).otherwise(_let(matches(j), with_match))

    first = F.struct(word(mask & ~((1 << edits) - 1)).alias("up"), word(0).alias("down"), (m - n).alias("sum"))
    columns = F.when(n > 0, F.sequence(F.lit(1), n)).otherwise(F.array().cast("array<int>"))
    return F.aggregate(columns, first, step, lambda s: s["sum"])


def edit_distance(x: Column, y: Column, edits: int) -> Column:
    """Edit distance of two texts if it is at most `edits`, else a larger number. Every step is bound to a variable of
    a lambda, so that no rewrite of the plan can copy it."""
    def ends_cut(s: Column) -> Column:
        return _let(common_prefix(s["a"], s["b"]), lambda n: _let(_after(s, n), starts_cut))

    def _after(s: Column, n: Column) -> Column:
        rest = lambda t: F.reverse(F.substring(t, n + 1, F.length(t)))
        return F.struct(rest(s["a"]).alias("a"), rest(s["b"]).alias("b"))

    def starts_cut(s: Column) -> Column:
        return _let(common_prefix(s["a"], s["b"]), lambda n: _let(_chars(s, n), lambda c: banded_distance(c["a"], c["b"], edits)))

    def _chars(s: Column, n: Column) -> Column:
        def chars(t: Column) -> Column:
            return F.when(F.length(t) > n, F.split(F.substring(t, n + 1, F.length(t)), "")).otherwise(F.array().cast("array<string>"))

        return F.struct(chars(s["a"]).alias("a"), chars(s["b"]).alias("b"))

    longer = F.length(x) >= F.length(y)
    ordered = F.struct(F.when(longer, x).otherwise(y).alias("a"), F.when(longer, y).otherwise(x).alias("b"))
    far = F.abs(F.length(x) - F.length(y)) > edits
    return F.when(far, F.lit(edits + 1)).otherwise(_let(ordered, ends_cut))


def within_edits(pairs: DataFrame, edits: int, limit: Column | None = None) -> DataFrame:
    """pairs with texts x, y -> those at most `edits` (and `limit`, if given) apart."""
    return pairs.where(edit_distance(F.col("x"), F.col("y"), edits) <= (F.lit(edits) if limit is None else limit))


def texts_at(rows: DataFrame, places: DataFrame) -> DataFrame:
    """doc_id, line_no, line of some places; the line numbers of a document travel as one set."""
    wanted = places.distinct().groupBy("doc_id").agg(F.collect_set("line_no").alias("wanted"))
    fetched = rows.join(wanted, "doc_id").select("doc_id", F.explode("wanted").alias("line_no"), F.split("text", "\n").alias("_all"))
    return fetched.select("doc_id", "line_no", F.get("_all", F.col("line_no")).alias("line")).distinct()


PAIR = ["doc_id", "line_no", "p_doc", "p_line"]
#: Pairs of one key are made of a line that is listed there and any other; of two that are, in one direction.
ONCE = "NOT p_own OR doc_id < p_doc OR (doc_id = p_doc AND line_no < p_line)"


def bounded(keys: DataFrame, tag: str) -> DataFrame:
    """Written keys, sent to every task while there are at most MAX_SENT, so that the lines stay where they are."""
    stored = materialize(keys, tag)
    return F.broadcast(stored) if stored.count() <= MAX_SENT else stored


def meetings(keyed: DataFrame, own: list[int]) -> tuple[DataFrame, DataFrame]:
    """keyed(lid, doc_id, line_no, len, keys) -> pairs of lines that are alone on a key, and the rows of keys with more lines.

    Keys are counted first, combined before the shuffle: most belong to one line, and of two lines the smaller and the larger
    number tell all. Only the keys with more lines are joined back: doc_id, line_no, len, key, own, long.
    """
    listed = F.col("pos").isin(own)
    rows = keyed.select("lid", F.posexplode("keys").alias("pos", "key")).where("key IS NOT NULL").select("lid", "key", listed.alias("own"))
    counts = rows.groupBy("key").agg(F.count_if("own").alias("o"), F.count("*").alias("n"), F.min("lid").alias("x"), F.max("lid").alias("y"))
    counts = materialize(counts.where("o > 0 AND x < y"), "key-counts")
    names = keyed.select(F.col("lid").alias("x"), "doc_id", "line_no")
    two = counts.where("n = 2").select("x", "y").distinct().join(names, "x")
    two = two.join(names.select(F.col("x").alias("y"), F.col("doc_id").alias("p_doc"), F.col("line_no").alias("p_line")), "y").select(*PAIR)
    more = counts.where("n > 2").select("key", (F.col("o") * F.col("n") > LONG_LIST).alias("long"))
    every = keyed.select("doc_id", "line_no", "len", F.posexplode("keys").alias("pos", "key")).where("key IS NOT NULL").withColumn("own", listed).drop("pos")
    return two, materialize(every.join(bounded(more, "more-keys"), "key").distinct(), "shared-keys")


def _named(rows: DataFrame) -> DataFrame:
    return rows.select(F.col("doc_id").alias("p_doc"), F.col("line_no").alias("p_line"), F.col("own").alias("p_own"), "key")


def first_candidates(two: DataFrame, shared: DataFrame) -> DataFrame:
    """Pairs (doc_id, line_no) and (p_doc, p_line): all of a short list; of a long one, each line with the earliest it can meet."""
    other = "(doc_id <> p_doc OR line_no <> p_line)"
    short, long_ = shared.where("NOT long"), shared.where("long")
    few = short.where("own").select("doc_id", "line_no", "key").join(_named(short), "key").where(f"{other} AND ({ONCE})")
    place = F.struct("doc_id", "line_no")
    heads = materialize(long_.groupBy("key").agg(F.min(F.when(F.col("own"), place)).alias("o"), F.min(place).alias("p")), "list-heads")
    by_own = heads.select("key", "o.*").join(_named(long_), "key").where(other)
    by_any = long_.where("own").select("doc_id", "line_no", "key").join(_named(heads.select("key", "p.*", F.lit(True).alias("own"))), "key").where(other)
    return two.union(few.select(*PAIR)).union(by_own.select(*PAIR)).union(by_any.select(*PAIR)).distinct()


def letter_counts(line: str) -> list[Column]:
    """How often each of LETTERS occurs, in either case."""
    return [F.length(line) - F.length(F.translate(F.col(line), c + c.upper(), "")) for c in LETTERS]


def open_candidates(rows: DataFrame, shared: DataFrame, removed: DataFrame, p: LineParams) -> DataFrame:
    """Pairs of long lists whose later line is not among the removed ones.

    Such lists belong to families of lines that differ in a word: letter counts are compared before a pair is made. Each
    edit changes their sum of differences by two at most, so no link is lost. Lines of one key are dealt over parts.
    """
    gone = removed.select("doc_id", "line_no", F.lit(True).alias("_gone"))
    members = shared.where("long").join(gone, ["doc_id", "line_no"], "left").withColumn("open", F.col("_gone").isNull()).drop("_gone", "long")
    place = F.struct("doc_id", "line_no")
    lists = members.groupBy("key").agg(F.max(F.when(F.col("open"), place)).alias("_last"), F.min(place).alias("_first"), F.count("*").alias("_m"))
    lists = lists.where("_last > _first").select("key", F.ceil(F.col("_m") / PART).cast("int").alias("parts"))
    members = materialize(members.join(lists, "key"), "open-lists")
    counted = texts_at(rows, members.select("doc_id", "line_no")).select("doc_id", "line_no", F.array(*letter_counts("line")).alias("counts"))
    members = materialize(members.join(counted, ["doc_id", "line_no"]), "open-members")
    part = F.pmod(F.xxhash64("doc_id", "line_no"), F.col("parts")).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.col("parts") - 1))
    theirs = [F.col("doc_id").alias("p_doc"), F.col("line_no").alias("p_line"), F.col("len").alias("p_len"), F.col("own").alias("p_own"), F.col("counts").alias("p_counts")]
    differ = sum((F.abs(F.col("counts")[k] - F.col("p_counts")[k]) for k in range(len(LETTERS))), F.lit(0))
    after = "(p_doc > doc_id OR (p_doc = doc_id AND p_line > line_no))"
    # the later line is open; one of both is listed under the key
    left = members.select("key", "doc_id", "line_no", "len", "own", "counts", every.alias("part"))
    right = members.where("open").select("key", part.alias("part"), *theirs)
    limit = 2 * allowed(F.least("len", "p_len"), p)
    return left.join(right, ["key", "part"]).where(F.expr(f"{after} AND (own OR p_own)") & (differ <= limit)).select(*PAIR).distinct()


def later_lines(rows: DataFrame, pairs: DataFrame, p: LineParams, tag: str) -> DataFrame:
    """doc_id, line_no of the later line of each pair that is near."""
    pairs = materialize(pairs, f"{tag}-pairs")
    texts = materialize(texts_at(rows, pairs.select("doc_id", "line_no").union(pairs.select("p_doc", "p_line"))), f"{tag}-texts")
    left = texts.select("doc_id", "line_no", F.col("line").alias("x"))
    right = texts.select(F.col("doc_id").alias("p_doc"), F.col("line_no").alias("p_line"), F.col("line").alias("y"))
    linked = within_edits(pairs.join(left, ["doc_id", "line_no"]).join(right, ["p_doc", "p_line"]), p.edits, allowed(F.least(F.length("x"), F.length("y")), p))
    later = F.greatest(F.struct("doc_id", "line_no"), F.struct(F.col("p_doc").alias("doc_id"), F.col("p_line").alias("line_no")))
    return materialize(linked.select(later.alias("z")).select("z.doc_id", "z.line_no").distinct(), f"{tag}-near")


def removed_lines(docs: DataFrame, p: LineParams = PRODUCTION) -> DataFrame:
    """documents -> doc_id, line_no, near (false: equal to an earlier line, true: near an earlier one)."""
    rows = of_type(docs, {"doc_id": "long", "text": "string"})
    lines = lines_of(rows).withColumn("len", F.length("line")).withColumn("k1", F.xxhash64("line")).withColumn("k2", F.xxhash64(F.lit(1), "line"))
    occurrences = lines.select("k1", "k2", "doc_id", "line_no").distinct()

    # exact: the first place of each different line
    firsts = occurrences.groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "line_no")).alias("f"), F.count("*").alias("m"))
    repeated = firsts.where("m > 1").select("k1", "k2", "f")
    equal = occurrences.join(repeated, ["k1", "k2"]).where("doc_id <> f.doc_id OR line_no <> f.line_no").select("doc_id", "line_no", F.lit(False).alias("near"))

    # near: keys of the different lines, at their first place
    keyed, own = with_keys(lines.where(F.col("len") >= p.chars_per_edit), p)
    keyed = keyed.select("k1", "k2", F.struct("doc_id", "line_no").alias("id"), "len", "keys")
    keyed = keyed.groupBy("k1", "k2").agg(F.min(F.struct("id", "len", "keys")).alias("x")).select(F.monotonically_increasing_id().alias("lid"), "x.id.doc_id", "x.id.line_no", "x.len", "x.keys")
    two, shared = meetings(materialize(keyed, "line-keys"), own)
    near = later_lines(rows, first_candidates(two, shared), p, "first")
    if not shared.where("long").isEmpty():
        near = near.unionByName(later_lines(rows, open_candidates(rows, shared, near, p), p, "open"))
    return equal.unionByName(near.withColumn("near", F.lit(True)))


def line_report(docs: DataFrame, p: LineParams = PRODUCTION) -> DataFrame:
    """documents -> doc_id, n_lines, n_equal, n_near, removed (line numbers from 0, ascending, joined by commas)."""
    rows = of_type(docs, {"doc_id": "long", "text": "string"})
    gone = removed_lines(docs, p).groupBy("doc_id").agg(
        F.count_if(~F.col("near")).alias("n_equal"), F.count_if(F.col("near")).alias("n_near"), F.array_sort(F.collect_set("line_no")).alias("_gone")
    )
    counted = rows.select("doc_id", F.coalesce(F.size(F.split("text", "\n")), F.lit(0)).cast("long").alias("n_lines"), F.col("text").isNull().alias("_none"))
    return counted.join(gone, "doc_id", "left").select(
        "doc_id",
        F.when(F.col("_none"), F.lit(0)).otherwise(F.col("n_lines")).cast("long").alias("n_lines"),
        F.coalesce("n_equal", F.lit(0)).alias("n_equal"),
        F.coalesce("n_near", F.lit(0)).alias("n_near"),
        F.coalesce(F.array_join("_gone", ","), F.lit("")).alias("removed"),
    )


def without_repeated_lines(docs: DataFrame, p: LineParams = PRODUCTION) -> DataFrame:
    """docs without the removed lines; n_chars follows, and documents left without any text go."""
    gone = removed_lines(docs, p).groupBy(F.col("doc_id").alias("_id")).agg(F.collect_set("line_no").alias("_gone"))
    joined = docs.join(gone, F.col("doc_id").cast("long") == F.col("_id"), "left")
    lines = F.split("text", "\n")
    left = F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("_gone")), lambda i: F.get(lines, i))
    text = F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(left, "\n"))
    out = joined.withColumn("text", text).where(F.col("_gone").isNull() | F.col("text").rlike(r"[^\s]"))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_gone").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_report(spark.read.parquet(f"{sf_dir}/documents.parquet"))

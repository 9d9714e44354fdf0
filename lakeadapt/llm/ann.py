"""Approximate nearest neighbours: an inverted file of coarse centroids with product-quantised residuals.

The model (centroids, one small codebook per slice of the dimensions) is fitted on a bounded sample: the `sample_rows`
vectors with the smallest hash, copies left out. All rows are indexed: nearest centroid and 8-bit codes of the residual. A query scores
the lists it probes with a table of inner products per code (asymmetric: the query is not quantised), keeps the
different vectors of each slice that can reach its result, and their exact inner products on the original vectors, taken
where the slice lies, decide. A score by codes is wrong by at most the query's length times the entry's distance to its codes,
and an entry is kept if the score raised by that reaches the k-th best of the sample: a probed list loses nothing. Copies of a vector are one entry with its k + 1 smallest ids, which loses nothing: they score
the same, and ties go to the smaller id.

How many lists a query probes is set twice: on the sample, against its exact neighbours there (`target_recall`), and on
`judged_queries` real queries, against their exact neighbours among all rows, so that it follows the data and the queries. A query that finds fewer than k rows so scans all lists without a lower bound. Lists are cut into slices of about
`slice_rows`; queries stream past a slice. Nothing but the model is sent to every task, and its size does not grow with the rows.

Defined cases: vectors that are null, zero, of another length than the sample's, or hold null or non-finite components
take no part; fewer candidates than k give all of them; ties go to the smaller vec_id; null ids take no part; an
empty table gives no rows. A vec_id names one vector: rows that repeat it are one candidate and one query, with the
smallest (in array order) of their vectors that can take part. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.llm.common import materialize, of_type


@dataclass(frozen=True)
class AnnParams:
    k: int = 20
    query_every: int = 20
    #: The sample holds `sample_per_list` rows a list, `sample_rows` at least and `most_sample` at most.
    sample_rows: int = 20_000
    sample_per_list: int = 16
    most_sample: int = 262_144
    code_slices: int = 16
    train_rounds: int = 8
    target_recall: float = 0.985
    #: Real queries that are compared with all rows, and what all but `judged_misses` of them must find.
    judged_queries: int = 256
    least_recall: float = 0.9
    judged_misses: float = 0.05
    #: By how many times its largest possible error the score of an entry is raised; 1 loses nothing.
    floor_errors: float = 1.0
    slice_rows: int = 20_000
    seed: int = 5


PRODUCTION = AnnParams()
#: Results that a scanning task holds before it merges them.
MERGE = 1 << 19


@dataclass(frozen=True)
class Model:
    centroids: np.ndarray
    books: np.ndarray
    probes: int
    sample: np.ndarray

    def assign(self, x: np.ndarray) -> np.ndarray:
        return _nearest(x, self.centroids)

    def encode(self, x: np.ndarray, lists: np.ndarray) -> np.ndarray:
        rest, (m, _, d) = x - self.centroids[lists], self.books.shape
        rest = np.pad(rest, ((0, 0), (0, m * d - rest.shape[1])))
        return np.stack([_nearest(rest[:, j * d : (j + 1) * d], self.books[j]) for j in range(m)], axis=1).astype(np.uint8)

    def errors(self, x: np.ndarray, codes: np.ndarray, at: int) -> np.ndarray:
        """How far the vectors of a list lie from what their codes stand for."""
        back = np.concatenate([self.books[j][c] for j, c in enumerate(codes.T)], axis=1)[:, : x.shape[1]]
        return np.linalg.norm(x - self.centroids[at] - back, axis=1)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """Inner products of each query with each code word: (queries, slices, 256)."""
        m, _, d = self.books.shape
        q = np.pad(q, ((0, 0), (0, m * d - q.shape[1]))).reshape(len(q), m, d)
        return np.einsum("qmd,mcd->qmc", q, self.books)


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    half = (centres**2).sum(1) / 2
    return np.concatenate([np.argmax(x[k : k + 8192] @ centres.T - half, axis=1) for k in range(0, len(x), 8192)]) if len(x) else np.zeros(0, np.int64)


def _kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    centres = x[rng.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        near = _nearest(x, centres)
        n = np.bincount(near, minlength=len(centres))
        order = np.argsort(near, kind="stable")
        sums = np.add.reduceat(x[order], np.concatenate([[0], np.cumsum(n)[:-1]]).clip(max=len(x) - 1), axis=0)
        centres = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centres)
    return centres


def list_count(n_rows: int, p: AnnParams) -> int:
    """Inverted lists: the square root of the rows, as far as the sample can place centroids."""
    return int(max(1, min(np.sqrt(n_rows), p.most_sample // p.sample_per_list)))


def sample_size(n_rows: int, p: AnnParams) -> int:
    return int(min(p.most_sample, max(p.sample_rows, p.sample_per_list * list_count(n_rows, p))))


def fit(sample: np.ndarray, n_rows: int, p: AnnParams) -> Model:
    rng = np.random.default_rng(p.seed)
    lists = min(list_count(n_rows, p), len(sample))
    centroids = _kmeans(sample, lists, p.train_rounds, rng)
    m = min(p.code_slices, sample.shape[1])
    d = -(-sample.shape[1] // m)
    near = _nearest(sample, centroids)
    rest = np.pad(sample - centroids[near], ((0, 0), (0, m * d - sample.shape[1])))
    size = min(256, len(sample))
    books = np.stack([_kmeans(rest[:, j * d : (j + 1) * d], size, p.train_rounds, rng) for j in range(m)])
    # lists to probe: enough for the wanted share of the exact neighbours of some sample rows
    asked = sample[rng.permutation(len(sample))[:200]]
    scores = asked @ sample.T
    top = np.argpartition(-scores, min(p.k, len(sample) - 1), axis=1)[:, : p.k + 1]
    ranks = np.argsort(np.argsort(-(asked @ centroids.T), axis=1), axis=1)
    needed = np.sort(np.take_along_axis(ranks, near[top], axis=1).ravel())
    probes = int(needed[min(len(needed) - 1, int(np.ceil(p.target_recall * len(needed))))]) + 1
    return Model(centroids, books, min(lists, probes), sample)


def probes_needed(index: DataFrame, asked: DataFrame, model: Model, p: AnnParams) -> int:
    """Lists to probe for the wanted share of the exact neighbours, among all rows, of the `judged_queries` queries of the
    smallest hashes. One pass over the index; what comes back is k rows a judged query."""
    drawn = asked.orderBy(F.xxhash64("vec_id"), "vec_id").limit(p.judged_queries).select("vec_id", "embedding").toArrow()  # at most judged_queries
    if not len(drawn):
        return model.probes
    own, q = drawn.column("vec_id").to_numpy(), _matrix(drawn.column("embedding").combine_chunks())

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scores, lists = np.full((len(q), p.k), -np.inf), np.zeros((len(q), p.k), np.int32)
        for batch in batches:
            x = np.frombuffer(b"".join(batch.column("x").to_pylist()), np.float64).reshape(len(batch), -1)
            new = q @ x.T
            new[(own[:, None] == batch.column("vec_id").to_numpy()[None, :]) & (batch.column("n").to_numpy() == 1)[None, :]] = -np.inf
            here = np.broadcast_to(batch.column("list").to_numpy()[None, :], new.shape)
            scores, lists = np.hstack([scores, new]), np.hstack([lists, here])
            top = np.argpartition(-scores, p.k - 1, axis=1)[:, : p.k]
            scores, lists = np.take_along_axis(scores, top, axis=1), np.take_along_axis(lists, top, axis=1)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(len(q)), p.k)), pa.array(lists.ravel()), pa.array(scores.ravel())], ["ask", "list", "score"])

    found = index.select("list", "vec_id", "x", F.size("ids").alias("n")).mapInArrow(best, "ask long, list int, score double").where(F.col("score") > float("-inf"))
    ranked = found.withColumn("_r", F.row_number().over(Window.partitionBy("ask").orderBy(F.col("score").desc(), "list"))).where(F.col("_r") <= p.k)
    top = ranked.select("ask", "list").toArrow()  # k rows a judged query
    if not len(top):
        return model.probes
    ask, lists = top.column("ask").to_numpy(), top.column("list").to_numpy()
    ranks = np.argsort(np.argsort(-(q @ model.centroids.T), axis=1, kind="stable"), axis=1)[ask, lists]
    pooled = np.sort(ranks)
    each = np.sort([np.sort(ranks[ask == a])[int(np.ceil(p.least_recall * (ask == a).sum())) - 1] for a in np.unique(ask)])
    at = lambda ordered, share: int(ordered[min(len(ordered) - 1, int(np.ceil(share * len(ordered))))])
    return min(len(model.centroids), max(model.probes, at(pooled, p.target_recall) + 1, at(each, 1 - p.judged_misses) + 1))


def valid(vectors: DataFrame) -> DataFrame:
    """vec_id, embedding (doubles): rows that can take part."""
    rows = of_type(vectors, {"vec_id": "long", "embedding": "array<double>"})
    sound = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return rows.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).where(sound & F.exists("embedding", lambda x: x != 0))


def one_per_id(rows: DataFrame) -> DataFrame:
    """rows(vec_id, embedding) with each vec_id once. Ids alone are counted; vectors move only where an id repeats."""
    repeated = materialize(rows.groupBy("vec_id").agg(F.count("*").alias("m")).where("m > 1").select("vec_id"), "repeated-ids")
    if repeated.isEmpty():
        return rows
    again = rows.join(repeated, "vec_id", "left_semi").groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    return materialize(rows.join(repeated, "vec_id", "left_anti").unionByName(again), "one-per-id")


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _merged(found: list[list], k: int) -> list[list]:
    """The k best of each query among (query_id, vec_id, score) pieces, ties to the smaller vec_id."""
    ask, ids, scores = (np.concatenate(c) for c in found)
    order = np.lexsort((ids, -scores, ask))
    ask, ids, scores = ask[order], ids[order], scores[order]
    keep = np.arange(len(ask)) - np.searchsorted(ask, ask) < k
    return [[ask[keep]], [ids[keep]], [scores[keep]]]


def search(vectors: DataFrame, p: AnnParams = PRODUCTION) -> DataFrame:
    """embeddings -> query_id, rank, vec_id, score for every vec_id that `query_every` divides."""
    spark = vectors.sparkSession
    rows = valid(vectors)
    shape = rows.agg(F.count("*").alias("n"), F.mode(F.size("embedding")).alias("dim")).head()
    out_schema = "query_id long, rank int, vec_id long, score double"
    if not shape["n"]:
        return spark.createDataFrame([], out_schema)
    rows = one_per_id(rows.where(F.size("embedding") == shape["dim"]))
    drawn = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_size(shape["n"], p)).select("embedding").toArrow()  # at most most_sample
    # copies of one vector would take the place of centroids and make the neighbours look easy to find
    model = fit(np.unique(_matrix(drawn.column(0).combine_chunks()), axis=0), shape["n"], p)
    sent = spark.sparkContext.broadcast(model)

    def indexed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        for batch in batches:
            x = _matrix(batch.column("embedding")) + 0.0  # no negative zeros
            lists = model.assign(x)
            codes, raw = model.encode(x, lists), [v.tobytes() for v in x]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(lists, pa.int32()), batch.column("vec_id"), pa.array([c.tobytes() for c in codes], pa.binary()),
                    pa.array(raw, pa.binary()), pa.array([xxhash.xxh3_128_digest(r) for r in raw], pa.binary()),
                ],
                ["list", "vec_id", "codes", "x", "sig"],
            )

    copies = Window.partitionBy("sig").orderBy("vec_id")
    index = rows.mapInArrow(indexed, "list int, vec_id long, codes binary, x binary, sig binary").withColumn("_r", F.row_number().over(copies)).where(F.col("_r") <= p.k + 1)
    own = F.min_by(F.struct("list", "vec_id", "codes", "x"), "vec_id").alias("own")
    index = materialize(index.groupBy("sig").agg(own, F.sort_array(F.collect_list("vec_id")).alias("ids")).select("own.*", "ids"), "ivf")
    asked = rows.where(F.col("vec_id") % p.query_every == 0)
    needed = probes_needed(index, asked, model, p)
    counts = index.groupBy("list").agg(F.count("*").alias("n"), F.sum(F.size("ids")).alias("ids")).collect()  # two numbers per list
    wanted = min(p.k, sum(r["ids"] for r in counts) - 1)
    slices = spark.createDataFrame([(r["list"], max(1, -(-r["n"] // p.slice_rows))) for r in counts], "list int, slices int")
    members = index.join(F.broadcast(slices), "list").select(
        "list", F.expr("cast(pmod(xxhash64(vec_id), slices) AS int)").alias("slice"), F.lit(0).alias("kind"), "vec_id", "codes", "x", "ids"
    )
    width = int(shape["dim"])

    def probing(everywhere: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            model = sent.value
            probes = len(model.centroids) if everywhere else needed
            for batch in batches:
                x, ids = _matrix(batch.column("embedding")), batch.column("vec_id").to_numpy()
                for k in range(0, len(x), 512):
                    q, own = x[k : k + 512], ids[k : k + 512]
                    near = q @ model.centroids.T
                    chosen = np.argpartition(-near, probes - 1, axis=1)[:, :probes]
                    floor = np.full(len(q), -np.inf)
                    if len(model.sample) > p.k and not everywhere:
                        # the k-th best of the sample bounds the result from below; the query itself may be in the sample
                        floor = -np.partition(-(q @ model.sample.T), p.k, axis=1)[:, p.k]
                    hit, at = chosen.ravel(), np.repeat(np.arange(len(q)), probes)
                    order = np.argsort(hit, kind="stable")
                    lists, cuts = np.unique(hit[order], return_index=True)
                    groups = np.split(at[order], cuts[1:])
                    payload = [np.hstack([own[g, None].view(np.float64), floor[g, None], near[g, lists[j], None], q[g]]).tobytes() for j, g in enumerate(groups)]
                    yield pa.RecordBatch.from_arrays([pa.array(lists, pa.int32()), pa.array(payload, pa.binary())], ["list", "codes"])

        return run

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, at, entries, names = sent.value, None, [], ["query_id", "vec_id", "score"]
        m = model.books.shape[0]
        held = None
        found: list[list] = [[], [], []]
        for batch in batches:
            for place, kind, vec_id, raw, x, ids in zip(
                zip(batch.column("list").to_pylist(), batch.column("slice").to_pylist()), *[batch.column(c).to_pylist() for c in ("kind", "vec_id", "codes", "x", "ids")]
            ):
                if place != at:
                    at, entries, held = place, [], None
                if kind == 0:
                    entries.append((vec_id, raw, x, ids))
                    continue
                if not entries:
                    continue
                if held is None:
                    first, codes, vectors, every = zip(*entries)
                    first, codes = np.array(first, np.int64), np.frombuffer(b"".join(codes), np.uint8).reshape(-1, m)
                    vectors = np.frombuffer(b"".join(vectors), np.float64).reshape(-1, width)
                    held = first, codes, vectors, every, np.array([len(e) == 1 for e in every]), model.errors(vectors, codes, place[0]), np.linalg.norm(vectors, axis=1)
                first, codes, vectors, every, single, errors, lengths = held
                asked = np.frombuffer(raw, np.float64).reshape(-1, width + 3)
                own, floor, near = asked[:, 0].copy().view(np.int64), asked[:, 1], asked[:, 2]
                for k in range(0, len(asked), 64):
                    tables = model.tables(asked[k : k + 64, 3:])
                    scores = np.repeat(near[k : k + 64, None], len(first), axis=1)
                    for j in range(m):
                        scores += tables[:, j, codes[:, j]]
                    # the largest error, and a little for what sums of doubles lose
                    size = np.linalg.norm(asked[k : k + 64, 3:], axis=1)[:, None]
                    scores += p.floor_errors * size * errors + 1e-9 * size * lengths
                    scores[(own[k : k + 64, None] == first[None, :]) & single[None, :]] = -np.inf
                    for i, best in enumerate(map(np.flatnonzero, scores >= np.maximum(floor[k : k + 64, None], -1e300))):
                        exact = vectors[best] @ asked[k + i, 3:]
                        # one more than k: a query comes first among its own copies, whose order its own id must not settle
                        top = np.lexsort((first[best], -exact))[: p.k + 1]
                        rows_of = [every[b] for b in best[top]]
                        ids = np.array([v for e in rows_of for v in e], np.int64)
                        exact = np.repeat(exact[top], [len(e) for e in rows_of])
                        exact, ids = exact[ids != own[k + i]], ids[ids != own[k + i]]
                        top = np.lexsort((ids, -exact))[: p.k]
                        found[0].append(np.full(len(top), own[k + i]))
                        found[1].append(ids[top])
                        found[2].append(exact[top])
            # a task holds many slices: only its k best of a query can matter
            if sum(map(len, found[0])) > MERGE:
                found = _merged(found, p.k)
                if 2 * len(found[0][0]) > MERGE:
                    yield pa.RecordBatch.from_arrays([pa.array(c[0]) for c in found], names)
                    found = [[], [], []]
        if found[0]:
            yield pa.RecordBatch.from_arrays([pa.array(c[0]) for c in _merged(found, p.k)], names)

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")

    def nearest(asked: DataFrame, everywhere: bool) -> DataFrame:
        queries = asked.mapInArrow(probing(everywhere), "list int, codes binary").join(F.broadcast(slices), "list").select(
            "list", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("slice"), F.lit(1).alias("kind"), F.lit(None).cast("long").alias("vec_id"), "codes",
            F.lit(None).cast("binary").alias("x"), F.lit(None).cast("array<long>").alias("ids"),
        )
        together = members.unionByName(queries).repartition(parts, "list", "slice").sortWithinPartitions("list", "slice", "kind", "vec_id")
        near = together.mapInArrow(scanned, "query_id long, vec_id long, score double")
        return near.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= p.k).select("query_id", "rank", "vec_id", "score")

    first = materialize(nearest(asked, False), "near")
    served = first.groupBy("query_id").agg(F.count("*").alias("n")).where(F.col("n") >= wanted).select(F.col("query_id").alias("vec_id"))
    short = materialize(asked.join(served, "vec_id", "left_anti").select("vec_id", "embedding"), "short")
    if short.isEmpty():
        return first
    return first.join(short.select(F.col("vec_id").alias("query_id")), "query_id", "left_anti").unionByName(nearest(short, True))


def op10_ivf_pq(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


#: The exact answer, in doubles: what the recall is measured against.
EXACT_SQL = """
SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(CAST(q.embedding AS DOUBLE[]), CAST(c.embedding AS DOUBLE[])) AS score
FROM embeddings q JOIN embeddings c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
"""

"""Token ids in a binary format: bit-plane shuffling.

Documents are cut into shards by ranges of doc_id and sorted inside; a shard's ids run end to end (each document with its end
id) and are cut into chunks of `chunk_ids`. A chunk is transposed into 16 or 32 bit planes (or 2 or 4 byte planes),
each compressed with zstandard on its own. The chunk row also says which documents begin in it and where, and the
chunk index (shard, chunk, ids before it, ids in it, bytes of its planes) is a table beside it: any run of ids is read from
the few chunks that hold it.

Reading back needs no shuffle of ids: a chunk gives whole documents, and for those that cross its ends a length and a
checksum that combine with those of its neighbours.

Defined cases: a null text is empty (its end id only); null doc_ids come first; ties on doc_id are ordered by a hash of
the text; an empty table gives empty files and no rows. Extra columns are ignored.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.llm.bpe import gather
from lakeadapt.llm.common import cut_points, materialize, new_path, of_type, range_bucket, task_count

END_ID = 1
#: Pieces of words that a Python worker remembers; the memory starts anew when it is full.
KNOWN_PIECES = 600_000
#: Texts that are cut into words together.
SLICE = 4_000
#: ASCII marks that are no part of a word: a run of them after a letter or digit is a token run of its own.
MARKS = ".,!?;:#$%&*"
CHUNK_SCHEMA = (
    "shard int, chunk int, first_id long, n_ids int, width int, planes array<binary>, doc_ids array<long>,"
    " doc_starts array<long>, head_id long, head_start long, open_end boolean"
)


class WordEncoder:
    """ids of whole texts through the tokenizer, asked once per piece of a word and worker.

    The tokenizer drops white space, lower-cases, and its rules never look across white space, nor from a letter or digit
    into the marks behind it; so the ids of a text are those of its words, and a word's those of its body and its marks.
    Words with a special token's opening are handed over as they are.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.forget()

    def forget(self) -> None:
        self.number: dict[str, int] = {"": 0}
        self.flat, self.lengths = np.zeros(0, np.uint16), np.zeros(1, np.uint8)

    def encode(self, texts: pa.Array) -> list[np.ndarray]:
        return [ids for k in range(0, len(texts), SLICE) for ids in self._slice(texts.slice(k, SLICE))]

    def _slice(self, texts: pa.Array) -> list[np.ndarray]:
        """Words are cut, counted and compared by Arrow; Python sees each different piece of the slice once."""
        if len(self.number) > KNOWN_PIECES:
            self.forget()
        number, new = self.number, []

        def piece(text: str) -> int:
            k = number.get(text)
            if k is None:
                number[text] = k = len(number)
                new.append(text)
            return k

        texts = pc.fill_null(texts, "")
        special = pc.match_substring(texts, "<|")
        words = pc.ascii_split_whitespace(pc.if_else(special, texts, pc.ascii_lower(texts)))
        coded = words.flatten().dictionary_encode()
        different = coded.dictionary
        body = pc.ascii_rtrim(different, characters=MARKS)
        cut = pc.and_(pc.match_substring_regex(body, "[a-z0-9]$"), pc.invert(pc.match_substring(different, "<|")))
        body = pc.if_else(cut, body, different)
        marks, size = np.zeros(len(different), np.int64), pc.utf8_length(body).to_numpy()
        marked = np.flatnonzero(size < pc.utf8_length(different).to_numpy())
        marks[marked] = [piece(w[n:]) for w, n in zip(different.take(pa.array(marked)).to_pylist(), size[marked].tolist())]
        bodies = body.dictionary_encode()
        at = np.fromiter(map(piece, bodies.dictionary.to_pylist()), np.int64, len(bodies.dictionary))
        parts = np.stack([at[bodies.indices.to_numpy()] if len(body) else marks, marks], axis=1)
        if new:
            batch = getattr(self.tokenizer, "encode_batch_fast", self.tokenizer.encode_batch)
            ids: list[list[int]] = []
            for k in range(0, len(new), 20_000):
                ids += [e.ids for e in batch(new[k : k + 20_000], add_special_tokens=False)]
            lengths = np.fromiter(map(len, ids), np.int64, len(ids))
            flat = np.fromiter(chain.from_iterable(ids), np.int64, int(lengths.sum()))
            wide = np.result_type(self.flat.dtype, np.min_scalar_type(int(flat.max(initial=0))))
            deep = np.result_type(self.lengths.dtype, np.min_scalar_type(int(lengths.max(initial=0))))
            self.flat, self.lengths = np.concatenate([self.flat, flat], dtype=wide, casting="unsafe"), np.concatenate([self.lengths, lengths], dtype=deep, casting="unsafe")
        lengths = self.lengths.astype(np.int64)
        starts, picks = np.cumsum(lengths) - lengths, coded.indices.to_numpy()
        every = gather(self.flat, starts, lengths, parts[picks].ravel()).astype(np.uint32)
        ends = np.concatenate([[0], np.cumsum(lengths[parts].sum(axis=1)[picks])])[words.offsets.to_numpy() - words.offsets[0].as_py()]
        return [every[i:j] for i, j in zip(ends[:-1].tolist(), ends[1:].tolist())]


@lru_cache(maxsize=2)
def _encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def to_planes(ids: np.ndarray, width: int, bits: bool = True, level: int = 3) -> list[bytes]:
    """ids below 2**(8 * width) -> compressed planes, lowest first."""
    import zstandard

    raw = ids.astype(f"<u{width}").view(np.uint8).reshape(len(ids), width)
    planes = np.packbits(np.unpackbits(raw, axis=1, bitorder="little").T, axis=1) if bits else np.ascontiguousarray(raw.T)
    squeeze = zstandard.ZstdCompressor(level=level)
    return [squeeze.compress(p.tobytes()) for p in planes]


def from_planes(planes: list[bytes], n: int, width: int) -> np.ndarray:
    import zstandard

    loosen = zstandard.ZstdDecompressor()
    rows = [np.frombuffer(loosen.decompress(p), np.uint8) for p in planes]
    if len(rows) == width:
        raw = np.ascontiguousarray(np.stack(rows).T)
    else:
        raw = np.packbits(np.unpackbits(np.stack(rows), axis=1, count=n).T, axis=1, bitorder="little")
    return np.ascontiguousarray(raw).view(f"<u{width}").ravel().astype(np.uint32)


def _gf2(matrix: list[int], vector: int) -> int:
    out, k = 0, 0
    while vector:
        if vector & 1:
            out ^= matrix[k]
        vector >>= 1
        k += 1
    return out


@lru_cache(maxsize=64)
def _zero_bytes(power: int) -> tuple[int, ...]:
    """What 2**power zero bytes do to a crc32, as a matrix over GF(2)."""
    if power == 0:
        step = [0xEDB88320, *(1 << k for k in range(31))]  # one zero bit
        for _ in range(3):
            step = [_gf2(step, x) for x in step]
        return tuple(step)
    half = _zero_bytes(power - 1)
    return tuple(_gf2(half, x) for x in half)


def crc32_join(first: int, second: int, n_bytes: int) -> int:
    """The crc32 of two byte strings end to end, from theirs and the length of the second."""
    power = 0
    while n_bytes >> power:
        if n_bytes >> power & 1:
            first = _gf2(_zero_bytes(power), first)
        power += 1
    return first ^ second


@dataclass(frozen=True)
class TokenFiles:
    spark: SparkSession
    path: str

    def chunks(self) -> DataFrame:
        return self.spark.read.schema(CHUNK_SCHEMA).parquet(f"{self.path}/chunks")

    def index(self) -> DataFrame:
        """shard, chunk, start (ids of all shards and chunks before it), n_ids, n_bytes."""
        return self.spark.read.parquet(f"{self.path}/index")


def write_tokens(docs: DataFrame, tokenizer_path: str, chunk_ids: int = 65_536, bits: bool = True, width: int = 2, shards: int | None = None) -> TokenFiles:
    """Encode documents in ascending doc_id order and write chunks and index to the shared folder."""
    spark = docs.sparkSession
    shards = shards or task_count(docs)
    docs = of_type(docs, {"doc_id": "long", "text": "string"})
    ranged = docs.withColumn("shard", range_bucket(F.col("doc_id"), cut_points(docs, "doc_id", shards)).cast("int"))
    ordered = ranged.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, schema = _encoder(tokenizer_path), None
        state: dict = {"shard": None}

        def begin(shard: int) -> None:
            state.update(shard=shard, chunk=0, first=0, at=0, buffer=[], held=0, ids=[], starts=[], head=(None, None), last=(None, None))

        def emit(n: int, ended: bool) -> dict:
            ids = np.concatenate(state["buffer"]) if state["buffer"] else np.zeros(0, np.uint32)
            out, rest = ids[:n], ids[n:]
            if len(out) and int(out.max()) >> (8 * width):
                raise ValueError(f"ids do not fit into {width} bytes")
            here = sum(s < state["first"] + n for s in state["starts"])
            row = {
                "shard": state["shard"], "chunk": state["chunk"], "first_id": state["first"], "n_ids": n, "width": width,
                "planes": to_planes(out, width, bits), "doc_ids": state["ids"][:here], "doc_starts": state["starts"][:here],
                "head_id": state["head"][0], "head_start": state["head"][1], "open_end": not ended,
            }
            last = (state["ids"][here - 1], state["starts"][here - 1]) if here else state["head"]
            state.update(
                chunk=state["chunk"] + 1, first=state["first"] + n, buffer=[rest] if len(rest) else [], held=len(rest),
                ids=state["ids"][here:], starts=state["starts"][here:], head=(None, None) if ended else last,
            )
            return row

        def full() -> Iterator[dict]:
            while state["held"] >= chunk_ids:
                cut = state["first"] + chunk_ids
                yield emit(chunk_ids, cut == state["at"] or cut in state["starts"])

        def close() -> Iterator[dict]:
            if state["shard"] is not None:
                yield from full()
                if state["held"]:
                    yield emit(state["held"], True)

        def batch_of(rows: list[dict]) -> pa.RecordBatch:
            nonlocal schema
            schema = schema or pa.schema([
                ("shard", pa.int32()), ("chunk", pa.int32()), ("first_id", pa.int64()), ("n_ids", pa.int32()), ("width", pa.int32()),
                ("planes", pa.list_(pa.binary())), ("doc_ids", pa.list_(pa.int64())), ("doc_starts", pa.list_(pa.int64())),
                ("head_id", pa.int64()), ("head_start", pa.int64()), ("open_end", pa.bool_()),
            ])
            return pa.RecordBatch.from_pylist(rows, schema)

        for batch in batches:
            rows: list[dict] = []
            ids = encoder.encode(batch.column("text"))
            for shard, doc_id, own in zip(batch.column("shard").to_pylist(), batch.column("doc_id").to_pylist(), ids):
                if shard != state["shard"]:
                    rows += close()
                    begin(shard)
                state["ids"].append(doc_id)
                state["starts"].append(state["at"])
                state["buffer"].append(np.append(own, np.uint32(END_ID)))
                state["at"] += len(own) + 1
                state["held"] += len(own) + 1
                if state["held"] >= chunk_ids:
                    rows += full()
            if rows:
                yield batch_of(rows)
        if rows := list(close()):
            yield batch_of(rows)

    files = TokenFiles(spark, new_path(spark, "tokens"))
    ordered.select("doc_id", "text", "shard").mapInArrow(run, CHUNK_SCHEMA).write.option("compression", "none").parquet(f"{files.path}/chunks")
    slim = files.chunks().select("shard", "chunk", "first_id", "n_ids", F.expr("aggregate(planes, 0L, (s, p) -> s + octet_length(p))").alias("n_bytes"))
    totals = slim.groupBy("shard").agg(F.sum("n_ids").alias("n"))  # one row per shard
    before = totals.select("shard", F.coalesce(F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    slim.join(F.broadcast(before), "shard").select("shard", "chunk", (F.col("_before") + F.col("first_id")).alias("start"), "n_ids", "n_bytes").write.parquet(f"{files.path}/index")
    return files


def read_pieces(files: TokenFiles) -> DataFrame:
    """Per chunk and document in it: shard, chunk, doc_id, doc_start (in the shard), n, crc, whole."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for c in batch.to_pylist():
                ids = from_planes(c["planes"], c["n_ids"], c["width"]).astype("<u4")
                starts, first, end = c["doc_starts"], c["first_id"], c["first_id"] + c["n_ids"]
                cuts = [*starts, end]
                if first < cuts[0]:  # goes on with a document of an earlier chunk
                    part = ids[: cuts[0] - first]
                    out.append((c["shard"], c["chunk"], c["head_id"], c["head_start"], len(part), zlib.crc32(part.tobytes()), False))
                for k, (doc_id, at) in enumerate(zip(c["doc_ids"], starts)):
                    part = ids[at - first : cuts[k + 1] - first]
                    whole = k + 1 < len(starts) or not c["open_end"]
                    out.append((c["shard"], c["chunk"], doc_id, at, len(part), zlib.crc32(part.tobytes()), whole))
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]
            cols = list(zip(*out)) if out else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["shard", "chunk", "doc_id", "doc_start", "n", "crc", "whole"])

    chunks = files.chunks().select("shard", "chunk", "first_id", "n_ids", "width", "planes", "doc_ids", "doc_starts", "head_id", "head_start", "open_end")
    return chunks.mapInArrow(run, "shard int, chunk int, doc_id long, doc_start long, n long, crc long, whole boolean")


def read_documents(files: TokenFiles) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files alone."""
    pieces = materialize(read_pieces(files), "pieces")  # so that the planes are opened once
    whole = pieces.where("whole").select("shard", "doc_id", "doc_start", "n", "crc")

    @F.pandas_udf("long")
    def joined(parts: pd.Series) -> pd.Series:
        def one(rows) -> int:
            crc = 0
            for x in rows:
                crc = crc32_join(crc, int(x["crc"]), 4 * int(x["n"]))
            return crc

        return parts.map(one)

    # the pieces of one document: as many as the chunks that it fills
    cut = pieces.where("NOT whole").groupBy("shard", "doc_start").agg(
        F.first("doc_id").alias("doc_id"), F.sum("n").alias("n"), F.array_sort(F.collect_list(F.struct("chunk", "n", "crc"))).alias("parts")
    ).select("shard", "doc_id", "doc_start", "n", joined("parts").alias("crc"))
    starts = files.index().where("chunk = 0").select("shard", F.col("start").alias("_before"))
    return whole.unionByName(cut).join(F.broadcast(starts), "shard").select(
        "doc_id", (F.col("_before") + F.col("doc_start")).alias("start"), F.col("n").alias("n_tokens"), F.col("crc").alias("ids_crc32")
    )


def read_ids(files: TokenFiles, start: int, n: int, most: int = 1 << 27) -> np.ndarray:
    """ids start..start+n-1 of the whole corpus, on the driver: only the chunks that the index names are read, `most` ids at once."""
    if n > most:
        raise ValueError(f"{n} ids asked for at once; read `TokenFiles.chunks` in Spark, or raise `most`")
    hit = files.index().where((F.col("start") < start + n) & (F.col("start") + F.col("n_ids") > start))
    rows = files.chunks().join(F.broadcast(hit.select("shard", "chunk", "start")), ["shard", "chunk"]).select("start", "n_ids", "width", "planes").orderBy("start").collect()
    parts = [from_planes(r["planes"], r["n_ids"], r["width"]) for r in rows]
    return np.concatenate(parts)[start - rows[0]["start"] :][:n] if parts else np.zeros(0, np.uint32)


def tokenizer_file() -> str:
    import public_tokenizers as public

    return public.path("word_bpe_49k.json")


def op6_bit_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_documents(write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), tokenizer_file()))

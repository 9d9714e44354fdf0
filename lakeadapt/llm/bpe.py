"""Byte-level BPE over a global shuffle of distinct words.

Texts are cut into pre-tokens. Documents travel in blocks of about `block_mb`: a block keeps, for every document, the
positions of its pre-tokens as codes of the block's own word list, and sends each word of that list once to the bucket
of its hash. A bucket sees all occurrences-by-block of its words, so every distinct word of the corpus is encoded once.
The ids go back to the blocks, where the codes put them into the order of the text. Decoding joins ids with the table
of token bytes.

What crosses the network is one entry per block and distinct word, twice, and the coded texts, once; a word that fills
the corpus is still one entry per block. Both passes cut blocks from the same scan; a block whose two passes disagree
raises instead of giving wrong ids, so docs must be a table or another input that reads the same twice.

Defined cases: a null text is empty (0 tokens); a text longer than a block is a block of its own; repeated rows are
encoded like any other; an empty table gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from lakeadapt.llm.common import of_type, task_count

#: Word lists are dealt to at least so many buckets; the coded texts of a block follow its buckets.
BUCKETS = 1024
FRAME = 1 << 30
SCHEMA = "block long, part int, payload binary"
_ARROW = pa.schema([("block", pa.int64()), ("part", pa.int32()), ("payload", pa.binary())])


@lru_cache(maxsize=4)
def codec(ranks_path: str):
    import tiktoken
    import public_tokenizers as public

    ranks = {}
    with open(ranks_path, "rb") as f:
        for line in f:
            if line.strip():
                token, rank = line.split()
                ranks[base64.b64decode(token)] = int(rank)
    return tiktoken.Encoding("ranks", pat_str=public.PATTERN, mergeable_ranks=ranks, special_tokens={}), ranks


@lru_cache(maxsize=4)
def token_table(ranks_path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of all tokens end to end; where each id begins; how long it is."""
    ranks = codec(ranks_path)[1]
    by_id = sorted((r, t) for t, r in ranks.items())
    size = by_id[-1][0] + 1
    lengths = np.zeros(size, np.int64)
    for r, t in by_id:
        lengths[r] = len(t)
    blob = np.frombuffer(b"".join(t for _, t in by_id), np.uint8)
    return blob, np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths


class _Units(dict):
    """Numbers strings in order of first sight; all instances that share `seen` share the numbers."""

    def __init__(self, seen: list[str], prefix: str):
        self.seen, self.prefix = seen, prefix

    def __missing__(self, key: str) -> int:
        self[key] = number = len(self.seen)
        self.seen.append(self.prefix + key)
        return number


def gather(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray, picks: np.ndarray) -> np.ndarray:
    """The runs flat[starts[p] : starts[p] + lengths[p]] for each p, end to end."""
    n = lengths[picks]
    ends = np.cumsum(n)
    if not len(ends) or not ends[-1]:
        return flat[:0]
    return flat[np.repeat(starts[picks] - (ends - n), n) + np.arange(ends[-1])]


#: White space beside a space.
_TOUCHED = re.compile(r" \s|\s ")


def split_block(texts: list[str], pattern) -> tuple[list[str], list[np.ndarray]]:
    """The different units of a block, and per text the numbers of its units: chunks between spaces, or pre-tokens.

    Where no white space stands next to a space, every pre-token that holds a space begins with it, so such a text is
    cut at its spaces first: a chunk with its leading space splits the same everywhere and is looked at once per block.
    Any other text goes through the pattern whole.
    """
    units: list[str] = []
    spaced, plain = _Units(units, " "), _Units(units, "")
    rows = []
    for text in texts:
        chunks = text.split(" ")
        if "" in chunks[1:] or _TOUCHED.search(text):
            picks = [plain[x] for x in pattern.findall(text)]
            rows.append(np.array(picks, np.int64))
            continue
        picks = np.fromiter(map(spaced.__getitem__, chunks), np.int64, len(chunks)) if len(chunks) > 1 else np.zeros(1, np.int64)
        if chunks[0] == "":
            picks = picks[1:] if len(chunks) > 1 else picks[:0]
        else:
            picks[0] = plain[chunks[0]]
        rows.append(picks)
    return units, rows


def _distinct(units: list[str], pattern, n_buckets: int = BUCKETS) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
    """Words in canonical order (bucket, word) with their buckets, and the codes of each unit, end to end."""
    number: dict[str, int] = {}
    flat, lengths = [], np.empty(len(units), np.int64)
    for k, unit in enumerate(units):
        words = pattern.findall(unit)
        lengths[k] = len(words)
        for w in words:
            flat.append(number.setdefault(w, len(number)))
    words = list(number)
    raw = [w.encode("utf-8", "surrogatepass") for w in words]
    keyed = sorted(zip((zlib.crc32(r) % n_buckets for r in raw), raw, range(len(words))))
    rank = np.empty(len(words), np.int64)
    rank[[k for _, _, k in keyed]] = np.arange(len(words))
    return [r for _, r, _ in keyed], np.array([b for b, _, _ in keyed], np.int32), rank[np.array(flat, np.int64)], lengths


def pack(*arrays: np.ndarray | bytes) -> bytes:
    import zstandard

    parts = [a if isinstance(a, bytes) else a.tobytes() for a in arrays]
    head = np.array([len(parts), *map(len, parts)], np.int64).tobytes()
    return zstandard.compress(head + b"".join(parts), 3)


def unpack(payload: bytes) -> list[bytes]:
    import zstandard

    raw = zstandard.decompress(payload)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    sizes, at, out = np.frombuffer(raw, np.int64, n, 8), 8 * (n + 1), []
    for size in sizes:
        out.append(raw[at : at + int(size)])
        at += int(size)
    return out


def _planes(codes: np.ndarray) -> bytes:
    """32-bit codes, first bytes first: compresses far better."""
    return np.ascontiguousarray(codes.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()


def _from_planes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(4, -1).T).view("<u4").ravel().astype(np.int64)


def _blocks(batches: Iterator[pa.RecordBatch], limit: int) -> Iterator[tuple[int, pa.Array, list[str]]]:
    ids, texts, size = [], [], 0

    def block():
        key = pa.concat_arrays(ids) if ids else pa.array([], pa.int64())
        digest = hashlib.blake2b(digest_size=8)
        for t in texts:
            digest.update(f"{len(t)}:{t[:64]}|".encode("utf-8", "surrogatepass"))
        digest.update(str(key.to_pylist()).encode())
        return int.from_bytes(digest.digest(), "little", signed=True), key, texts

    for batch in batches:
        start = 0
        for k, text in enumerate(batch.column("text").to_pylist()):
            texts.append(text or "")
            size += 4 * len(texts[-1]) // 3 + 1
            if size >= limit:
                ids.append(batch.column("doc_id").slice(start, k + 1 - start))
                yield block()
                ids, texts, size, start = [], [], 0, k + 1
        if start < batch.num_rows:
            ids.append(batch.column("doc_id").slice(start))
    if texts:
        yield block()


def _rows(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows), _ARROW)], schema=_ARROW)


def encode_documents(docs: DataFrame, ranks_path: str, block_mb: int = 32, with_ids: bool = False, parts: int | None = None) -> DataFrame:
    """documents -> doc_id, n_tokens, ids_sha256, decoded_sha256 and, if asked for, the ids themselves (array<int>)."""
    parts = parts or task_count(docs)
    n_buckets = max(BUCKETS, 4 * parts)
    docs = of_type(docs, {"doc_id": "long", "text": "string"})
    limit = block_mb << 20

    def words_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pattern = _pattern()
        for block, _, texts in _blocks(batches, limit):
            words, buckets, _, _ = _distinct(split_block(texts, pattern)[0], pattern, n_buckets)
            cuts = np.searchsorted(buckets, np.arange(n_buckets + 1))
            rows = []
            for b in range(n_buckets):
                own = words[cuts[b] : cuts[b + 1]]
                if own:
                    rows.append((block, b, pack(np.array([len(w) for w in own], np.uint32), b"".join(own))))
            if rows:
                yield _rows(rows)

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = codec(ranks_path)[0]
        bucket, known = -1, {}
        for batch in batches:
            rows = []
            for block, part, payload in zip(*(batch.column(k).to_pylist() for k in range(3))):
                if part != bucket:
                    bucket, known = part, {}
                sizes, blob = unpack(payload)
                ends = np.cumsum(np.frombuffer(sizes, np.uint32).astype(np.int64)).tolist()
                out, counts, at = [], [], 0
                for end in ends:
                    word = blob[at:end]
                    at = end
                    ids = known.get(word)
                    if ids is None:
                        known[word] = ids = encoding.encode_ordinary(word.decode("utf-8", "surrogatepass"))
                    out += ids
                    counts.append(len(ids))
                rows.append((block, part, pack(np.array(counts, np.uint32), np.array(out, np.uint32))))
            if rows:
                yield _rows(rows)

    def frames_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pattern = _pattern()
        for block, ids, texts in _blocks(batches, limit):
            units, picks = split_block(texts, pattern)
            words, _, flat, lengths = _distinct(units, pattern, n_buckets)
            starts = np.cumsum(lengths) - lengths
            codes = [gather(flat, starts, lengths, p) for p in picks]
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, pa.schema([("doc_id", pa.int64())])) as w:
                w.write_batch(pa.RecordBatch.from_arrays([ids], ["doc_id"]))
            counts = np.array([len(c) for c in codes], np.int64)
            coded = np.concatenate(codes) if codes else np.zeros(0, np.int64)
            yield _rows([(block, FRAME, pack(np.array([len(words)], np.int64), sink.getvalue().to_pybytes(), counts, _planes(coded)))])

    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", *(["ids"] if with_ids else [])]

    def reassembled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blob, at, size = token_table(ranks_path)
        block, counts, ids = None, [], []
        for batch in batches:
            for own, part, payload in zip(*(batch.column(k).to_pylist() for k in range(3))):
                if own != block:
                    block, counts, ids = own, [], []
                if part != FRAME:
                    n, flat = unpack(payload)
                    counts.append(np.frombuffer(n, np.uint32).astype(np.int64))
                    ids.append(np.frombuffer(flat, np.uint32))
                    continue
                n_words, keys, n_codes, planes = unpack(payload)
                lengths = np.concatenate(counts) if counts else np.zeros(0, np.int64)
                flat = np.concatenate(ids) if ids else np.zeros(0, np.uint32)
                if len(lengths) != int(np.frombuffer(n_words, np.int64)[0]):
                    raise ValueError("the two passes over the texts cut different blocks: write the input to a table first")
                starts = np.cumsum(lengths) - lengths
                codes, cut = _from_planes(planes), np.concatenate([[0], np.cumsum(np.frombuffer(n_codes, np.int64))])
                docs_ = pa.ipc.open_stream(keys).read_all().column(0).combine_chunks()
                rows: list[list] = [[] for _ in names[1:]]
                first = 0
                for k in range(len(cut) - 1):
                    out = gather(flat, starts, lengths, codes[cut[k] : cut[k + 1]])
                    rows[0].append(len(out))
                    rows[1].append(hashlib.sha256(out.astype("<u4").tobytes()).hexdigest())
                    rows[2].append(hashlib.sha256(gather(blob, at, size, out).tobytes()).hexdigest())
                    if with_ids:
                        rows[3].append(out.astype(np.int32))
                    if k + 1 - first >= 1000 or k + 2 == len(cut):
                        kinds = [pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32())]
                        yield pa.RecordBatch.from_arrays([docs_.slice(first, k + 1 - first), *(pa.array(c, t) for c, t in zip(rows, kinds))], names)
                        rows, first = [[] for _ in names[1:]], k + 1

    lists = docs.mapInArrow(words_of, SCHEMA).repartition(parts, "part").sortWithinPartitions("part")
    back = lists.mapInArrow(encoded, SCHEMA).unionByName(docs.mapInArrow(frames_of, SCHEMA))
    whole = back.repartition(parts, "block").sortWithinPartitions("block", "part")
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if with_ids else "")
    return whole.mapInArrow(reassembled, schema)


def decode_ids(encoded: DataFrame, ranks_path: str) -> DataFrame:
    """doc_id, ids array<int> -> doc_id, decoded binary."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blob, at, size = token_table(ranks_path)
        for batch in batches:
            out = [gather(blob, at, size, np.asarray(x or [], np.int64)).tobytes() for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.binary())], ["doc_id", "decoded"])

    return of_type(encoded, {"doc_id": "long", "ids": "array<int>"}).mapInArrow(run, "doc_id long, decoded binary")


@lru_cache(maxsize=1)
def _pattern():
    import public_tokenizers as public
    import regex

    return regex.compile(public.PATTERN)


def ranks_file() -> str:
    import public_tokenizers as public

    return public.path("byte_bpe_multi_50k.tiktoken")


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), ranks_file())

"""Byte-level BPE encoding by overlapping chunks, and decoding.

A text is cut into chunks that overlap. Each chunk is pre-tokenised on its own; two neighbouring
chunks are stitched at the first boundary that both have inside their overlap. From a common
boundary on, the scan depends on nothing before it, so the stitched pieces are exactly those of
one scan over the whole text. The pieces are then merged by rank, each on its own.

A text of one chunk is worked on where its row is. The chunks of longer texts are rows, dealt to
tasks by text and number; each distinct text is encoded once, whatever the number of its copies.

Cases: null and empty texts have no ids; repeated rows give repeated results; an empty table gives
an empty one; a text with an overlap without a common boundary is scanned once more in one task,
with overlaps that are widened until there is one; columns named `token_ids` or `n_tokens` are
replaced, all others ride along.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from heapq import heapify, heappop, heappush
from struct import pack

import numpy as np
import pandas as pd
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StringType, StructField, StructType

from .common import bound_batches, read_table, small_batches, stage

CHUNK, OVERLAP = 1 << 16, 1 << 10
#: Pieces whose ids are remembered before the memory is emptied.
REMEMBERED = 1 << 18
#: Characters after a match that its end may depend on: the longest literal alternative of the pattern.
LOOKAHEAD = 3
#: Bytes up to which a pre-token's pairs are searched through rather than kept in a heap.
SHORT_PIECE = 256
#: Rows of a batch that hold a chunk, a long text or its ids each.
LONG_ROWS = 16
NEVER = 1 << 40


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def merge_piece(raw: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The ids of one pre-token: of all neighbours the pair of the lowest rank merges first, of equal pairs the left one."""
    if raw in ranks:
        return [ranks[raw]]
    if len(raw) > SHORT_PIECE:
        return _merge_by_heap(raw, ranks)
    parts = [raw[i : i + 1] for i in range(len(raw))]
    pairs = [ranks.get(raw[i : i + 2], NEVER) for i in range(len(raw) - 1)]
    while pairs and (low := min(pairs)) < NEVER:
        i = pairs.index(low)
        parts[i] += parts.pop(i + 1)
        del pairs[i]
        if i:
            pairs[i - 1] = ranks.get(parts[i - 1] + parts[i], NEVER)
        if i < len(pairs):
            pairs[i] = ranks.get(parts[i] + parts[i + 1], NEVER)
    return [ranks[x] for x in parts]


def _merge_by_heap(raw: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same for long pre-tokens: parts are known by where they start, merges wait in a heap."""
    n = len(raw)
    end, before = list(range(1, n + 1)), list(range(-1, n - 1))
    waiting = [(ranks[raw[i : i + 2]], i, i + 2) for i in range(n - 1) if raw[i : i + 2] in ranks]
    heapify(waiting)

    def offer(a: int, b: int) -> None:
        if (rank := ranks.get(raw[a:b])) is not None:
            heappush(waiting, (rank, a, b))

    while waiting:
        _, a, b = heappop(waiting)
        mid = end[a]
        if not mid or mid >= n or end[mid] != b:  # one of the two has merged otherwise
            continue
        end[a], end[mid] = b, 0
        if b < n:
            before[b] = a
            offer(a, end[b])
        if before[a] >= 0:
            offer(before[a], b)
    return [ranks[raw[a:b]] for a, b in enumerate(end) if b]


def settled(chunk_start: int, chunk_end: int, starts: list[int], ends: list[int], last: bool) -> int:
    """How many leading matches of a chunk don't depend on what follows the chunk."""
    n = len(starts)
    while not last and n and (ends[n - 1] >= chunk_end or starts[n - 1] + LOOKAHEAD > chunk_end):
        n -= 1
    return n


def chunk_pieces(text: str, find, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[str]:
    """The pre-tokens of `text`, found chunk by chunk."""
    if len(text) <= chunk:
        return [m.group() for m in find.finditer(text)]
    out: list[str] = []
    spans = _spans(text, find, 0, min(len(text), chunk))
    while True:
        begin, end, starts, ends = spans
        if end == len(text):
            out.extend(text[a:b] for a, b in zip(starts, ends))
            return out
        n = settled(begin, end, starts, ends, False)
        back = overlap
        while True:
            at = max(begin + 1, end - back)
            nxt = _spans(text, find, at, min(len(text), at + max(chunk, 2 * back)))
            n_next = settled(nxt[0], nxt[1], nxt[2], nxt[3], nxt[1] == len(text))
            have = {p: i for i, p in enumerate(nxt[2][:n_next])}
            i = int(np.searchsorted(starts, at + 1))
            while i < n and starts[i] not in have:
                i += 1
            if i < n:
                break
            if at == begin + 1:  # nothing common: one longer chunk from the last sure boundary
                k = max(0, n - 1)
                out.extend(text[a:b] for a, b in zip(starts[:k], ends[:k]))
                start = starts[k] if starts else begin
                spans = _spans(text, find, start, min(len(text), start + 2 * (end - start) + chunk))
                i = -1
                break
            back *= 2
        if i < 0:
            continue
        out.extend(text[a:b] for a, b in zip(starts[:i], ends[:i]))
        j = have[starts[i]]
        spans = (starts[i], nxt[1], nxt[2][j:], nxt[3][j:])


def _spans(text: str, find, begin: int, end: int) -> tuple[int, int, list[int], list[int]]:
    part = text[begin:end]
    ends = [begin + m.end() for m in find.finditer(part)]
    starts = [begin + m.start() for m in find.finditer(part)]
    return begin, end, starts, ends


class _Memory(dict):
    """piece -> its ids as little-endian unsigned 32-bit integers."""

    def __init__(self, encode):
        self.encode = encode

    def __missing__(self, piece: str) -> bytes:
        if len(self) >= REMEMBERED:
            self.clear()
        ids = pack(f"<{len(found := self.encode(piece))}I", *found)
        if len(piece) <= 64:
            self[piece] = ids
        return ids


class ByteBpe:
    """Encodes and decodes with the ranks and the pattern given. `chunk` and `overlap` are in characters."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP):
        self.find = regex.compile(pattern)
        self.chunk, self.overlap = chunk, overlap
        self.memory = _Memory(lambda piece: merge_piece(piece.encode("utf-8"), ranks))
        size = max(ranks.values()) + 1
        self.bytes_of = [b""] * size
        for raw, i in ranks.items():
            self.bytes_of[i] = raw

    def pieces(self, text: str) -> list[str]:
        if len(text) <= self.chunk:
            return self.find.findall(text)
        return chunk_pieces(text, self.find, self.chunk, self.overlap)

    def encode(self, text: str) -> bytes:
        return b"".join(map(self.memory.__getitem__, self.pieces(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


_LOADED: dict[tuple, ByteBpe] = {}


def _codec(path: str, pattern: str, chunk: int, overlap: int) -> ByteBpe:
    key = (path, pattern, chunk, overlap)
    if key not in _LOADED:
        _LOADED[key] = ByteBpe(load_ranks(path), pattern, chunk, overlap)
    return _LOADED[key]


def token_ids(text: Column, rank_file: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> Column:
    """The ids of a text as binary, little-endian unsigned 32 bits each. `rank_file` is a path on every executor."""

    @F.pandas_udf(BinaryType())
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        codec = _codec(rank_file, pattern, chunk, overlap)
        for texts in batches:
            yield pd.Series([codec.encode(t or "") for t in texts], dtype=object)

    return run(text)


def decoded_bytes(ids: Column, rank_file: str, pattern: str) -> Column:
    """The bytes that the ids stand for, one after another."""

    @F.pandas_udf(BinaryType())
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        codec = _codec(rank_file, pattern, CHUNK, OVERLAP)
        for col in batches:
            yield pd.Series([codec.decode(x or b"") for x in col], dtype=object)

    return run(ids)


DIGEST = StructType([StructField("n_tokens", LongType()), StructField("ids_sha256", StringType()), StructField("decoded_sha256", StringType())])


def _digest(codec: ByteBpe, ids: bytes) -> tuple[int, str, str]:
    return len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(codec.decode(ids)).hexdigest()


def token_digest(text: Column, rank_file: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> Column:
    """Encodes and decodes within one pass and keeps digests only, so ids need not travel."""

    @F.pandas_udf(DIGEST)
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        codec = _codec(rank_file, pattern, chunk, overlap)
        for texts in batches:
            yield pd.DataFrame([_digest(codec, codec.encode(t or "")) for t in texts], columns=DIGEST.names)

    return run(text)


def ids_digest(ids: Column, rank_file: str, pattern: str) -> Column:
    """The same digests of ids that are there already."""

    @F.pandas_udf(DIGEST)
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        codec = _codec(rank_file, pattern, CHUNK, OVERLAP)
        for col in batches:
            yield pd.DataFrame([_digest(codec, bytes(x)) for x in col], columns=DIGEST.names)

    return run(ids)


def default_files() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def scan_chunk(codec: ByteBpe, begin: int, part: str, chunk: int, overlap: int, last: bool) -> tuple:
    """One chunk's ids, and where it may be stitched: the boundaries within an overlap of its own start and of the
    next chunk's, each with the number of ids before it. `part` starts at `begin` and reaches an overlap into the next."""
    _, end, starts, ends = _spans(part, codec.find, 0, len(part))
    n = settled(0, end, starts, ends, last)
    found = [codec.memory[part[a:b]] for a, b in zip(starts[:n], ends[:n])]
    at = [0, *np.cumsum([len(x) // 4 for x in found], dtype=np.int64).tolist()]
    marks = [(begin + a, k) for a, k in zip(starts[:n], at)] + ([(begin + end, at[-1])] if last else [])
    head = [m for m in marks if m[0] <= begin + overlap]
    tail = [m for m in marks if m[0] >= begin + chunk]
    return [p for p, _ in head], [k for _, k in head], [p for p, _ in tail], [k for _, k in tail], b"".join(found)


def stitch(scans: list[tuple]) -> bytes | None:
    """The ids of a whole text from the scans of its chunks in order; None if two neighbours share no boundary."""
    out, first = [], 0
    for (_, _, tail, tail_at, ids), (head, head_at, _, _, _) in zip(scans, scans[1:]):
        starts_at = dict(zip(head, head_at))
        k = next((k for k, p in enumerate(tail) if p in starts_at), None)
        if k is None:
            return None
        out.append(ids[4 * first : 4 * tail_at[k]])
        first = starts_at[tail[k]]
    return b"".join([*out, scans[-1][4][4 * first :]])


def encode_long(texts: DataFrame, rank_file: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """(key, token_ids) of the distinct values of the column `text`, none of them null; `key` is the text's SHA-256.
    Chunks are scanned and encoded in tasks of their own, then a text's ids are put together where boundaries agree."""
    if not 0 < overlap <= chunk:
        raise ValueError("an overlap is positive and no longer than a chunk")
    spark = texts.sparkSession

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = ["key", "i", "last", "part"]
        rows: list[tuple] = []
        for pdf in batches:
            for key, text in zip(pdf["key"], pdf["text"]):
                for i in range(max(1, -(-len(text) // chunk))):
                    stop = (i + 1) * chunk + overlap
                    rows.append((key, i, stop >= len(text), text[i * chunk : stop]))
                    if len(rows) == LONG_ROWS:
                        yield pd.DataFrame(rows, columns=names)
                        rows = []
        yield pd.DataFrame(rows, columns=names)

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec = _codec(rank_file, pattern, chunk, overlap)
        for pdf in batches:
            rows = [(r.key, r.i, *scan_chunk(codec, r.i * chunk, r.part, chunk, overlap, r.last)) for r in pdf.itertuples()]
            yield pd.DataFrame(rows, columns=["key", "i", "head", "head_at", "tail", "tail_at", "ids"])

    def join(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = pdf.sort_values("i")
        scans = [tuple(r) for r in rows[["head", "head_at", "tail", "tail_at", "ids"]].itertuples(index=False)]
        return pd.DataFrame([(rows["key"].iloc[0], stitch(scans))], columns=["key", "token_ids"])

    with small_batches(spark, LONG_ROWS):
        whole = stage(texts.select(F.sha2("text", 256).alias("key"), "text").groupBy("key").agg(F.first("text").alias("text")), "bpe-texts")
        chunks = whole.mapInPandas(cut, "key string, i long, last boolean, part string").repartition("key", "i")
        marks = "head array<long>, head_at array<long>, tail array<long>, tail_at array<long>"
        scans = chunks.mapInPandas(scan, f"key string, i long, {marks}, ids binary")
        found = stage(scans.groupBy("key").applyInPandas(join, "key string, token_ids binary"), "bpe-ids")
        lost = whole.join(found.where("token_ids IS NULL").select("key"), "key", "left_semi")
        again = lost.select("key", token_ids(F.col("text"), rank_file, pattern, chunk, overlap).alias("token_ids"))
        return found.where("token_ids IS NOT NULL").unionByName(stage(again, "bpe-again"))


def _is_long(text: Column, chunk: int) -> Column:
    return F.coalesce(F.char_length(text) > chunk, F.lit(False))


def encode_documents(docs: DataFrame, rank_file: str, pattern: str, text_col: str = "text", chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """`docs` with `token_ids` (binary, little-endian unsigned 32 bits each) and `n_tokens`. `docs` is read more than once."""
    bound_batches(docs.sparkSession)
    text = F.col(text_col)
    short = docs.where(~_is_long(text, chunk)).withColumn("token_ids", token_ids(text, rank_file, pattern, chunk, overlap))
    rest = docs.where(_is_long(text, chunk))
    found = encode_long(rest.select(text.alias("text")), rank_file, pattern, chunk, overlap).withColumnsRenamed({"key": "_bpe_of", "token_ids": "_bpe_ids"})
    whole = rest.withColumn("_bpe_key", F.sha2(text, 256)).join(found, F.col("_bpe_key") == F.col("_bpe_of"))
    ids = short.unionByName(whole.withColumn("token_ids", F.col("_bpe_ids")).drop("_bpe_key", "_bpe_of", "_bpe_ids"))
    return ids.withColumn("n_tokens", (F.octet_length("token_ids") / 4).cast("long"))


def digest_documents(docs: DataFrame, rank_file: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """doc_id and the digests of every row of `docs` (doc_id, text); ids of long texts meet their rows as digests."""
    spark = docs.sparkSession
    bound_batches(spark)
    text = F.col("text")
    short = docs.where(~_is_long(text, chunk)).select("doc_id", token_digest(text, rank_file, pattern, chunk, overlap).alias("d"))
    rest = docs.where(_is_long(text, chunk))
    found = encode_long(rest.select("text"), rank_file, pattern, chunk, overlap)
    with small_batches(spark, LONG_ROWS):
        digests = stage(found.select("key", ids_digest(F.col("token_ids"), rank_file, pattern).alias("d")), "bpe-digests")
    whole = rest.select("doc_id", F.sha2("text", 256).alias("key")).join(digests, "key").select("doc_id", "d")
    return short.unionByName(whole).select("doc_id", "d.*")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_documents(read_table(spark, sf_dir, "documents", "doc_id", "text"), *default_files())

"""Byte-level BPE of whole texts, with tree concatenation for long text that the pattern does not split.

Most texts hold only short pieces (what the pre-tokenizer's pattern yields) and are encoded where they lie. A text with
a run of LONG_RUN or more characters that the pattern cannot split is taken apart: the long piece is cut into chunks,
the chunks of all texts are dealt out and encoded in parallel, and neighbours are joined in a tree. At each join
a window of tokens around the seam is decoded to bytes and encoded again; it grows until its outer token on either
side equals the token that stood there before. As a sequence is the encoding of its bytes exactly when every pair of
neighbours is the encoding of the pair's bytes, an agreeing window makes the whole sequence exact.

Nulls count as empty texts: no ids, decoded text empty. The special string of the vocabulary in a text becomes its id."""

from __future__ import annotations

import os
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import partitions, ship

LONG_RUN = 4096
CHUNK_BYTES = 4096
#: Up to here both libraries' character classes were compared (test_common_characters_agree); other texts use the slower one.
COMMON = re.compile("[^\x00-ɏ]")
OUT = "ids binary, decoded string"


@lru_cache(4)
def _library(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(4)
def _alphabet() -> tuple[str, dict[str, int]]:
    """Byte-level models write byte b as a printable character: itself if printable in Latin-1, else 256 upwards."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    spare = iter(range(256, 512))
    chars = "".join(chr(b) if b in shown else chr(next(spare)) for b in range(256))
    return chars, {c: b for b, c in enumerate(chars)}


@lru_cache(4)
def _quick(path: str):
    """The same vocabulary in the faster library, built from the tokenizer's own file; None where that file says more than
    byte-level pieces by the usual pattern."""
    import json

    import tiktoken

    spec = json.load(open(path, encoding="utf-8"))
    usual = {"type": "ByteLevel", "add_prefix_space": False, "use_regex": True}
    if spec.get("normalizer") or any((spec.get("pre_tokenizer") or {}).get(k) != v for k, v in usual.items()):
        return None
    special = {t["content"]: t["id"] for t in spec["added_tokens"]}
    _, back = _alphabet()
    ranks = {bytes(back[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
    pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)


@lru_cache(4)
def _bare(path: str):
    """Only the merges: encodes a byte string as one piece."""
    import json

    from tokenizers import Tokenizer, models

    spec = json.load(open(path, encoding="utf-8"))
    merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
    return Tokenizer(models.BPE(vocab=spec["model"]["vocab"], merges=merges))


@lru_cache(4)
def _token_bytes(path: str) -> list[bytes]:
    tool = _bare(path)
    _, back = _alphabet()
    vocab = tool.get_vocab()
    out = [b""] * (max(vocab.values()) + 1)
    for token, i in vocab.items():
        out[i] = bytes(back.get(c, 63) for c in token)
    return out


def encode_piece(path: str, piece: bytes) -> list[int]:
    chars, _ = _alphabet()
    return _bare(path).encode(piece.decode("latin-1").translate({b: chars[b] for b in range(256)}), add_special_tokens=False).ids if piece else []


def join(path: str, left: list[int], right: list[int]) -> list[int]:
    """The encoding of the bytes of left and right together, from the encodings of each."""
    if not left or not right:
        return left + right
    bits, k = _token_bytes(path), 2
    while True:
        a, b = left[-k:], right[:k]
        again = encode_piece(path, b"".join(bits[i] for i in a + b))
        whole_left, whole_right = k >= len(left), k >= len(right)
        if (whole_left or again[0] == a[0]) and (whole_right or again[-1] == b[-1]) and len(again) > 1 or whole_left and whole_right:
            return left[: max(0, len(left) - k)] + again + right[k:]
        k *= 2


def tree(path: str, parts: list[list[int]]) -> list[int]:
    while len(parts) > 1:
        parts = [join(path, parts[i], parts[i + 1]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return parts[0] if parts else []


def pieces(path: str, text: str) -> list[tuple[str, bytes]]:
    """A text as ('whole', short pieces' text, run together) and ('long', a long piece's bytes) in order.

    Cuts are made only where the pattern cuts, so that each part is encoded as it is within the text."""
    tool, out = _library(path), []
    special = [t.content for t in tool.get_added_tokens_decoder().values()]
    for segment in re.split("(" + "|".join(map(re.escape, special)) + ")", text) if special else [text]:
        if segment in special:
            out.append(("whole", segment.encode()))
            continue
        begun = last = 0
        for _, (a, b) in tool.pre_tokenizer.pre_tokenize_str(segment):
            if b - a >= LONG_RUN:
                # the piece before it goes alone: white space at the end of a part would be split otherwise
                out += [("pieces", segment[begun:last].encode())] * (last > begun)
                out += [("long", segment[max(begun, last) : a].encode())] * (a > max(begun, last)) + [("long", segment[a:b].encode())]
                begun = b
            last = a if b - a < LONG_RUN else b
        if begun < len(segment):
            out.append(("pieces", segment[begun:].encode()))
    return out


def _encode(path: str, texts: list[str]) -> list:
    quick, slow = _quick(path), _library(path)
    return [slow.encode(t, add_special_tokens=False).ids if not quick or COMMON.search(t) else quick.encode(t, allowed_special="all") for t in texts]


def _decoded(path: str, ids: list[int]) -> str:
    return _library(path).decode(ids, skip_special_tokens=False)


def encode(docs: DataFrame, path: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, ids binary of little-endian uint32, decoded string) for every row of docs, keys repeated as they are."""

    ship(docs.sparkSession)
    whole = F.coalesce(F.col(text), F.lit(""))
    kind = dict(docs.dtypes)[key]
    held = docs.select(F.col(key).alias("key"), whole.alias("text"), whole.rlike(rf"\S{{{LONG_RUN - 1}}}|\s{{{LONG_RUN - 1}}}").alias("long"))

    def plain(batches):
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                ids = _encode(path, part.column(1).to_pylist())
                slow = _library(path)
                yield pa.record_batch([part.column(0), pa.array([np.array(x, "<u4").tobytes() for x in ids], pa.binary()), pa.array(slow.decode_batch(ids, skip_special_tokens=False), pa.string())], ["key", "ids", "decoded"])

    def cut(batches):
        for batch in batches:
            for row, (key_, t, uid) in enumerate(zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)):
                for n, (what, data) in enumerate(pieces(path, t)):
                    chunks = [data[i : i + CHUNK_BYTES] for i in range(0, len(data), CHUNK_BYTES)] if what == "long" else [data]
                    m = len(chunks)
                    yield pa.record_batch([pa.array([key_.as_py()] * m, batch.column(0).type), pa.array([uid] * m, pa.int64()), pa.array([n] * m, pa.int32()), pa.array(range(m), pa.int32()), pa.array([what] * m), pa.array(chunks, pa.binary())], ["key", "uid", "n", "chunk", "what", "data"])

    def encode_parts(batches):
        for batch in batches:
            what, data = batch.column(4).to_pylist(), batch.column(5).to_pylist()
            ids = [encode_piece(path, d) if w == "long" else _encode(path, [d.decode()])[0] for w, d in zip(what, data, strict=True)]
            yield pa.record_batch([*batch.columns[:4], pa.array([np.array(x, "<u4").tobytes() for x in ids], pa.binary())], ["key", "uid", "n", "chunk", "ids"])

    def put_together(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table["n"].to_pylist(), table["chunk"].to_pylist(), table["ids"].to_pylist(), strict=True))
        ids: list[int] = []
        at = 0
        while at < len(rows):
            end = at
            while end < len(rows) and rows[end][0] == rows[at][0]:
                end += 1
            ids += tree(path, [np.frombuffer(r[2], "<u4").tolist() for r in rows[at:end]])
            at = end
        return pa.table([table["key"].combine_chunks().slice(0, 1), pa.array([np.array(ids, "<u4").tobytes()], pa.binary()), pa.array([_decoded(path, ids)])], ["key", "ids", "decoded"])

    short = held.filter("not long").select("key", "text").mapInArrow(plain, f"key {kind}, {OUT}")
    long = held.filter("long").select("key", "text", F.monotonically_increasing_id().alias("uid")).mapInArrow(cut, f"key {kind}, uid long, n int, chunk int, what string, data binary")
    long = long.repartition(partitions(docs.sparkSession), "uid", "n", "chunk").mapInArrow(encode_parts, f"key {kind}, uid long, n int, chunk int, ids binary")
    long = long.groupBy("uid").applyInArrow(put_together, f"key {kind}, {OUT}")
    return short.unionByName(long).withColumnRenamed("key", key)


def decode(encoded: DataFrame, path: str, ids: str = "ids", key: str = "doc_id") -> DataFrame:
    """(key, decoded string) of rows with ids as little-endian uint32; null ids give an empty text."""
    ship(encoded.sparkSession)

    def run(batches):
        for batch in batches:
            held = [np.frombuffer(x or b"", "<u4").tolist() for x in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array(_library(path).decode_batch(held, skip_special_tokens=False), pa.string())], [key, "decoded"])

    return encoded.select(key, ids).mapInArrow(run, f"{key} {dict(encoded.dtypes)[key]}, decoded string")

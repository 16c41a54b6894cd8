"""WARC archives of Zstandard frames: a dictionary in a leading skippable frame, then one frame for each record.

Writers roll over at ROLL_BYTES and rename each finished file, so a repeated task leaves the same names. Readers stream,
decode frame by frame with the file's own dictionary, and check version, headers, lengths and digests."""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh_path, partitions, ship, staged
from .jaccard import BROADCAST_IDS

MAGIC = 0x184D2A5D
ROLL_BYTES = 64 << 20
LEVEL = 3
#: The dictionary is fitted on about so many payloads' first SAMPLE_BYTES; it changes sizes, never contents.
SAMPLE_ROWS, SAMPLE_BYTES, DICTIONARY_BYTES = 400, 8192, 32768
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


class Damaged(ValueError):
    """An archive that breaks the format."""


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page}')}>"


def record(page, url: str | None, payload: bytes, refers_to=None) -> bytes:
    """A response record, or a revisit without payload that refers to a page's response."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + (payload if refers_to is None else b"")
    target = "".join(c if c > " " and c != "\x7f" else f"%{ord(c):02X}" for c in url or "")
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page)}", f"WARC-Date: {DATE}", *[f"WARC-Target-URI: {target}"] * bool(target), f"WARC-Payload-Digest: sha1:{digest(payload)}", f"X-Page-ID: {page}"]
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(refers_to)}", f"X-Refers-To-Page: {refers_to}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(head).encode() + block + b"\r\n\r\n"


def parse(data: bytes) -> tuple[dict, bytes]:
    """Headers (names in lower case) and payload of a whole record, checked."""
    head, gap, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not gap or lines[0] != "WARC/1.1":
        raise Damaged(f"not a record: {data[:40]!r}")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.partition(":")
        if not colon:
            raise Damaged(f"not a header: {line!r}")
        fields[name.strip().lower()] = value.strip()
    missing = {"warc-type", "warc-record-id", "warc-date", "content-length"} - set(fields)
    if missing or not fields["content-length"].isdigit():
        raise Damaged(f"headers missing or wrong: {sorted(missing) or 'content-length'}")
    size = int(fields["content-length"])
    if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
        raise Damaged(f"{fields['warc-record-id']}: {len(rest) - 4} bytes where {size} are said")
    http, gap, payload = rest[:size].partition(b"\r\n\r\n")
    length = next((int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")), None)
    if not gap or length is None:
        raise Damaged(f"{fields['warc-record-id']}: no HTTP header")
    fields["payload-length"] = length
    if fields["warc-type"] == "response" and (len(payload) != length or f"sha1:{digest(payload)}" != fields.get("warc-payload-digest")):
        raise Damaged(f"{fields['warc-record-id']}: payload and digest differ")
    return fields, payload


def leading(dictionary: bytes) -> bytes:
    return struct.pack("<II", MAGIC, len(dictionary)) + dictionary


def frames(stream, step: int = 1 << 16):
    """The decoded frames of an archive, one at a time."""
    import zstandard as Z

    head = stream.read(8)
    if len(head) < 8 or struct.unpack("<II", head)[0] != MAGIC:
        raise Damaged("no leading dictionary frame")
    size = struct.unpack("<II", head)[1]
    dictionary = stream.read(size)
    if len(dictionary) != size:
        raise Damaged("the dictionary is cut off")
    tool = Z.ZstdDecompressor(dict_data=Z.ZstdCompressionDict(dictionary)) if size else Z.ZstdDecompressor()
    data = stream.read(step)
    while data:
        frame, out = tool.decompressobj(), []
        while True:
            try:
                out.append(frame.decompress(data))
            except Z.ZstdError as e:
                raise Damaged(f"a frame can't be decoded: {e}") from e
            if frame.eof:
                data = frame.unused_data or stream.read(step)
                break
            data = stream.read(step)
            if not data:
                raise Damaged("the last frame is cut off")
        yield b"".join(out)


def fit_dictionary(pages: DataFrame, html: str = "html") -> bytes:
    """Empty where there are too few payloads to fit one."""
    import zstandard as Z

    some = pages.select(F.col(html).alias("html")).filter("length(html) > 0")
    total = some.count()
    if total > SAMPLE_ROWS:
        some = some.filter(F.pmod(F.xxhash64("html"), F.lit(total)) < SAMPLE_ROWS)
    held = [r[0].encode() for r in some.select(F.substring("html", 1, SAMPLE_BYTES)).limit(4 * SAMPLE_ROWS).collect()]
    try:
        return Z.train_dictionary(DICTIONARY_BYTES, held).as_bytes() if len(held) >= 16 else b""
    except Z.ZstdError:
        return b""


def revisits(pages: DataFrame, least: int = 0, key: str = "page_id", html: str = "html") -> DataFrame:
    """(id, refers_to) of the pages whose payload, of at least so many bytes, a smaller key also has."""
    body = F.coalesce(F.col(html), F.lit(""))
    rows = pages.select(F.col(key).alias("id"), F.sha2(body, 256).alias("sha"), F.octet_length(body).alias("size")).filter(F.col("size") >= least)
    several = rows.groupBy("sha").agg(F.min("id").alias("refers_to"), F.count("*").alias("n")).filter("n > 1").drop("n")
    return rows.join(several, "sha").filter("id <> refers_to").select("id", "refers_to")


def write(pages: DataFrame, least: int = 0, key: str = "page_id", url: str = "url", html: str = "html", to: str | None = None) -> DataFrame:
    """Archives of all pages in a shared folder; (file, records, bytes) of each. A null payload is an empty one."""
    import pyarrow.fs as fs

    spark = pages.sparkSession
    ship(spark)
    to = to or fresh_path(spark, "warc")
    dictionary = fit_dictionary(pages, html)
    again = staged(revisits(pages, least, key, html).dropDuplicates(["id"]), "revisits")
    small = again.count() * 16 <= BROADCAST_IDS
    rows = pages.select(F.col(key).alias("id"), F.col(url).alias("url"), F.coalesce(F.col(html), F.lit("")).alias("html"))
    rows = rows.join(F.broadcast(again) if small else again.hint("merge"), "id", "left").select("id", "url", "html", "refers_to")

    def run(batches):
        import zstandard as Z
        from pyspark import TaskContext

        task = TaskContext.get()
        store, top = fs.FileSystem.from_uri(to)
        store.create_dir(top, recursive=True)
        options = {"dict_data": Z.ZstdCompressionDict(dictionary)} if dictionary else {}
        tool = Z.ZstdCompressor(level=LEVEL, **options)
        sink, done, roll, count, size = None, [], 0, 0, 0

        def close():
            sink.close()
            store.move(f"{top}/.{name}.{task.taskAttemptId()}", f"{top}/{name}")
            done.append((f"{top}/{name}", count, size))

        for batch in batches:
            for page, address, body, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if sink is None:
                    name = f"part-{task.partitionId():06d}-{roll:04d}.warc.zst"
                    sink, count, size = store.open_output_stream(f"{top}/.{name}.{task.taskAttemptId()}", compression=None), 0, 0
                    size += sink.write(leading(dictionary)) or 0
                frame = tool.compress(record(page, address, body.encode(), refers))
                sink.write(frame)
                count, size = count + 1, size + len(frame)
                if size >= ROLL_BYTES:
                    close()
                    sink, roll = None, roll + 1
        if sink is not None:
            close()
        if done:
            yield pa.record_batch([pa.array([d[0] for d in done]), pa.array([d[1] for d in done], pa.int64()), pa.array([d[2] for d in done], pa.int64())], ["file", "records", "bytes"])

    made = staged(rows.mapInArrow(run, "file string, records long, bytes long"), "archives")
    scheme = to.partition("://")[0] if "://" in to else "file"
    return made.withColumn("store", F.lit(f"{scheme}:///" if scheme == "file" else to))


def read(archives: DataFrame, payload: bool = False) -> DataFrame:
    """Every record of the archives (file, store): page_id, payload_bytes, payload_digest, record_type, refers_to [, payload]."""
    import pyarrow.fs as fs

    ship(archives.sparkSession)
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
    wide = len(names) - (not payload)

    def run(batches):
        for batch in batches:
            for file, at in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                store, _ = fs.FileSystem.from_uri(at)
                held: list = []
                with store.open_input_stream(file, compression=None) as stream:
                    for data in frames(stream):
                        fields, body = parse(data)
                        refers = fields.get("x-refers-to-page")
                        held.append((int(fields["x-page-id"]), fields["payload-length"], fields["warc-payload-digest"].removeprefix("sha1:"), fields["warc-type"], None if refers is None else int(refers), body))
                        if len(held) == 500:
                            yield pa.record_batch([pa.array([h[i] for h in held], kinds[i]) for i in range(wide)], names[:wide])
                            held = []
                if held:
                    yield pa.record_batch([pa.array([h[i] for h in held], kinds[i]) for i in range(wide)], names[:wide])

    spread = archives.select("file", "store").repartition(partitions(archives.sparkSession))
    return spread.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", payload binary" * payload)

"""Secret scans: fixed patterns, and strings that compress badly where secrets are kept.

The base kinds assign, access and hex are patterns. The method's kind, novel, looks at long strings
of letters, digits and signs, of both letters and digits or of mixed case, near a sensitive word: it compresses the
text around the string with and without it, by zstandard primed with a dictionary of identifiers and
code, and reports the string if each of its characters costs more than NOVEL bytes. Names and paths cost
little, for their parts are in the dictionary or nearby; random strings cost nearly what their alphabet
holds. A novel string that overlaps a base span is left out, for the base span reports it.

Defined results: a null text is empty; spans count code points, their end exclusive, sorted by start, then
kind in the order of KINDS; rows with a null or repeated doc_id each get a row; other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession

from subwin.llm.common import map_batches, table, texts

KINDS = ("assign", "access", "hex", "novel")
#: The base patterns, and the least length of what counts.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS, HEX = re.compile(r"AKIA[A-Z0-9]+"), re.compile(r"[0-9a-f]{24,}")
LEAST_ASSIGN, LEAST_ACCESS, LEAST_HEX = 6, 20, 24

#: Candidates: at least 12 characters of the base64 alphabets, of a letter and a digit or of a lower-case letter before a capital, with
#: '=' only as padding, so that a name before '=' belongs to the surroundings; and words that make their surroundings sensitive.
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_-])(?=[A-Z0-9+/_-]*[a-z][a-z+/_-]*[A-Z0-9]|[a-z0-9+/_-]*[A-Z][A-Z+/_-]*[0-9]|[+/_-]*[0-9][0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]{12,}(?:={1,2}(?![A-Za-z0-9+/_=-]))?")
SENSITIVE = re.compile(r"passw|pwd|secret|token|api.?key|credential|private.?key|access.?key|auth|bearer|signature|(?<![A-Za-z0-9])key(?![A-Za-z0-9])|ssh-|BEGIN", re.IGNORECASE)
AROUND, NOVEL = 120, 0.8
#: Identifiers and code that the compressor knows beforehand.
IDENTIFIERS = """
import from return function class public private static const let var new this self def async await export default string integer boolean number array object null none true false undefined
getUser setUser userName userId accountId sessionId requestId clientId customerId orderId productId createdAt updatedAt deletedAt timestamp datetime configuration settings environment variable parameter argument
application/json text/html charset utf-8 content-type authorization bearer basic access_token refresh_token client_secret client_id api_key apiKey secret_key private_key public_key password passwd username email address
https://www.example.com/api/v1/users/ http://localhost:8080/index.html /usr/local/bin /home/user/.config /var/log/ src/main/java/com/example/ node_modules package.json requirements.txt README.md LICENSE Dockerfile docker-compose.yml
assertEquals assertTrue toString hashCode equals length push append insert remove update delete select where order group having limit offset join inner outer left right create table index primary foreign references
controller service repository manager factory builder handler listener adapter interface abstract implementation exception response request message template component module version release snapshot production development staging testing
HTTP_REQUEST_TIMEOUT_SECONDS MAX_RETRY_COUNT DEFAULT_BUFFER_SIZE ENABLE_DEBUG_LOGGING DATABASE_CONNECTION_URL AWS_REGION SERVER_PORT_NUMBER CACHE_EXPIRATION_MINUTES unknown-linux-gnu x86_64 arm64 sha256 sha512 md5 base64 utf8 http2 level compression internationalization
0123456789 abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ 2020-01-01T00:00:00Z 127.0.0.1 255.255.255.0 #ffffff #000000 1234567890 00000000-0000-0000-0000-000000000000
"""  # fmt: skip


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """start, number of the kind, end of the base kinds."""
    spans = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_ASSIGN]
    spans += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    spans += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(spans)


class Novelty:
    """Marginal compressed bytes by zstandard, primed with a dictionary."""

    def __init__(self, dictionary: str = IDENTIFIERS):
        primed = zstandard.ZstdCompressionDict(dictionary.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        self._compress = zstandard.ZstdCompressor(level=19, dict_data=primed, write_content_size=False, write_checksum=False).compress

    def cost(self, before: str, string: str, after: str) -> float:
        """Bytes that each character of ``string`` adds to the compressed text around it."""
        around = len(self._compress((before + after).encode()))
        return (len(self._compress((before + string + after).encode())) - around) / len(string)


def novel_spans(text: str, known: list[tuple[int, int, int]], novelty: Novelty, least: float = NOVEL) -> list[tuple[int, int, int]]:
    out = []
    for m in CANDIDATE.finditer(text):
        start, end = m.span()
        before, after = text[max(0, start - AROUND) : start], text[end : end + AROUND]
        if any(a < end and start < b for a, _, b in known) or not SENSITIVE.search(before + " " + after):
            continue
        if novelty.cost(before, m[0], after) >= least:
            out.append((start, 3, end))
    return out


def scan_secrets(docs: DataFrame, dictionary: str = IDENTIFIERS, least: float = NOVEL) -> DataFrame:
    """doc_id and its spans, an array of kind, start, end, of each document (doc_id, text)."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        novelty, found = Novelty(dictionary), []
        for text in texts(batch):
            base = base_spans(text)
            found.append([{"kind": KINDS[k], "start": a, "end": b} for a, k, b in sorted(base + novel_spans(text, base, novelty, least))])
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, kind)], names=["doc_id", "found"])

    id_type = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {id_type}, found array<struct<kind:string,start:int,end:int>>")


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = "array_join(transform(filter(found, x -> {}), x -> concat_ws(':', x.kind, x.start, x.end)), ',')"
    count = "cast(size(filter(found, x -> x.kind = '{0}')) as bigint) AS n_{0}"
    base = joined.format("x.kind <> 'novel'")
    return scan_secrets(table(spark, sf_dir, "documents")).selectExpr("doc_id", *[count.format(k) for k in KINDS[:3]], f"sha2({base}, 256) AS base_sha256", joined.format("true") + " AS spans")



"""Secret scan: fixed patterns and dictionary-primed zstandard novelty.

Base spans come from three patterns.  The novelty method looks at long tokens
that stand close behind a sensitive word: the token is compressed by a
zstandard compressor primed with a dictionary of common identifiers and the
code around it, and its marginal bytes (with the token, less without) per
character tell how much of it neither the surroundings nor the identifiers
explain.  Tokens above ``novelty`` become spans of kind ``novel``.

Null text is empty and has no spans.  Ties do not arise: a base span wins over
a novel one that it overlaps.  Repeated rows get equal results, an empty table no row.  Extra columns pass through ``find`` and
``mask`` untouched; where one has the name of a result, the result's name gets an underscore behind it.
"""

from __future__ import annotations

import bisect
import hashlib
import itertools
import re

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import free_names, prepare, tidy

KINDS = ("assign", "access", "hex", "novel")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ASSIGN_START = re.compile(r"password|passwd|secret|token|api_?key", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
# Words that make the text behind them sensitive, and identifiers common in code.
SENSITIVE = ("password", "passwd", "passphrase", "pwd", "secret", "token", "apikey", "api_key", "api-key", "access_key", "private_key", "client_secret", "credential", "authorization", "bearer", "auth", "signature", "session_id", "connection_string", "ssh-rsa")
IDENTIFIERS = (
    "import from return class def function const let var public private static void int string bool true false null None self this "
    "config settings environment variable value default example placeholder username password secret token api_key access_key client_id client_secret "
    "https:// http:// localhost example.com www index.html application/json Content-Type Authorization Bearer Basic getElementById addEventListener "
    "0123456789 abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ your_password_here changeme xxxxxxxxxxxxxxxx 00000000000000000000"
)
SENSITIVE_RE = re.compile(r"(?:" + "|".join(map(re.escape, sorted(SENSITIVE, key=len, reverse=True))) + r")[^A-Za-z0-9]", re.IGNORECASE | re.ASCII)
CANDIDATE = re.compile(r"[A-Za-z0-9+/_.=-]{16,}")
REACH, AROUND = 48, 256
NOVELTY = 0.55


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the three patterns, leftmost and non-overlapping per kind."""
    out = []
    if ("=" in text or ":" in text) and ASSIGN_START.search(text):
        out += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [(*m.span(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return out


def marginal_bytes(token: str, before: str, after: str, identifiers: str = IDENTIFIERS) -> int:
    """Compressed bytes that the token adds to its surroundings."""
    prime = zstandard.ZstdCompressionDict((identifiers + " " + before + " " + after).encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    zip_ = zstandard.ZstdCompressor(level=3, dict_data=prime, write_content_size=False, write_checksum=False, write_dict_id=False)
    near = before[-32:].encode()
    return len(zip_.compress(near + token.encode())) - len(zip_.compress(near))


def novel_spans(text: str, novelty: float = NOVELTY) -> list[tuple[int, int, str]]:
    """Incompressible tokens that begin within REACH characters behind a sensitive word."""
    out, done = [], 0
    for m in SENSITIVE_RE.finditer(text):
        last = m.end() + REACH
        while c := CANDIDATE.search(text, max(done, m.end() - 1), last + 16):
            s = c.start()
            e = CANDIDATE.match(text, s).end()
            done = e
            tok = text[s:e]
            if any(x.isdigit() for x in tok) and any(x.isalpha() for x in tok) and marginal_bytes(tok, text[max(0, s - AROUND) : s], text[e : e + AROUND]) >= novelty * len(tok):
                out.append((s, e, "novel"))
    return out


def all_spans(text: str, novelty: float = NOVELTY) -> tuple[list, list]:
    """Base spans, and base and novel spans together, by start and then kind."""
    order = {k: i for i, k in enumerate(KINDS)}
    base = base_spans(text)
    starts = sorted(b[0] for b in base)
    reach = list(itertools.accumulate((b[1] for b in sorted(base)), max))  # how far the spans up to here go
    more = [x for x in novel_spans(text, novelty) if not (i := bisect.bisect_left(starts, x[1])) or reach[i - 1] <= x[0]]
    key = lambda x: (x[0], order[x[2]], x[1])
    return sorted(base, key=key), sorted(base + more, key=key)


def joined(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def find(docs: DataFrame, novelty: float = NOVELTY) -> DataFrame:
    """docs and columns base_spans, spans: arrays of struct(start, end, kind)."""
    prepare(docs.sparkSession)
    kind = T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("kind", T.StringType())]))
    own = free_names(docs.columns, "base_spans", "spans")
    arrow = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string())]))

    def work(it):
        for batch in it:
            texts = batch.column(batch.schema.get_field_index("text"))
            got = [all_spans(t or "", novelty) for a in range(0, len(texts), 256) for t in texts.slice(a, 256).to_pylist()]
            cols = [pa.array([[{"start": s, "end": e, "kind": k} for s, e, k in g[i]] for g in got], arrow) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *cols], names=[*batch.schema.names, *own])

    return docs.mapInArrow(tidy(work), T.StructType([*docs.schema.fields, *[T.StructField(n, kind) for n in own]]))


def redact(text: str | None, spans, word: str = "[SECRET]") -> str | None:
    """The text with each span, overlapping ones as one, replaced by word."""
    if not text or not spans:
        return text
    out, at = [], 0
    end = -1
    for s, e in sorted((x["start"], x["end"]) for x in spans):
        if s >= end:
            out += [text[at:s], word]
            at = end = e
        elif e > end:
            at = end = e
    return "".join([*out, text[at:]])


def mask(docs: DataFrame, novelty: float = NOVELTY) -> DataFrame:
    """docs with every span replaced by ``[SECRET]``, and n_masked, the number of spans."""
    prepare(docs.sparkSession)
    (count,) = free_names(docs.columns, "n_masked")

    def work(it):
        for batch in it:
            at = batch.schema.get_field_index("text")
            texts, n = [], []
            for a in range(0, batch.num_rows, 256):
                for t in batch.column(at).slice(a, 256).to_pylist():
                    spans = all_spans(t or "", novelty)[1]
                    texts.append(redact(t, [{"start": s, "end": e} for s, e, _ in spans]))
                    n.append(len(spans))
            cols = list(batch.columns)
            cols[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*cols, pa.array(n, pa.int32())], names=[*batch.schema.names, count])

    return docs.mapInArrow(tidy(work), T.StructType([*docs.schema.fields, T.StructField(count, T.IntegerType())]))


def digest(docs: DataFrame, novelty: float = NOVELTY) -> DataFrame:
    """One row per document: counts by kind, hash of the base spans, all spans."""
    f = find(docs.select("doc_id", F.col("text").cast("string").alias("text")), novelty)
    line = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("base_spans", lambda x: x["kind"] == k)).cast("long")
    return f.select("doc_id", *[count(k).alias(f"n_{k}") for k in KINDS[:3]], F.sha2(line("base_spans"), 256).alias("base_sha256"), line("spans").alias("spans"))


def sha256_of_spans(spans) -> str:
    return hashlib.sha256(joined(spans).encode()).hexdigest()

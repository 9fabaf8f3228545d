"""Interleaved documents: ordered text and media references parsed from HTML, payloads resolved by digest.

A *sequence* is an array of structs (pos, kind, text, digest): kind ``text`` carries a run of text, kind ``media`` a
reference (the ``data-digest`` of an ``img``, ``video`` or ``audio`` element, else ``src:`` and its address) with its
caption: the ``figcaption`` of the enclosing figure, before or after its media and for all of them, else ``alt``.
Positions count from 0 in reading order. A ``head`` ends at ``</head>`` or where the body begins; other hidden elements
that are never closed hide nothing but their own tag.

Payloads lie in a *store*: a Parquet table (digest, media) in which ``media`` is a binary greymap: a header, then
rows of 64 8-bit samples. Each task stores a payload once, however many documents share it (the texts themselves are
not exchanged for this), and what several tasks stored is collapsed before the join: one row a digest. References meet
the store in an equi-join on the digest.

Features are computed from the samples that were read back: mean and deviation, the entropy of their histogram, and the
shares of eight equal ranges of brightness.

Defined cases: null HTML or text counts as empty; an empty payload is one row of 64 zero samples; a reference
without a stored payload keeps its position and caption with null features; repeated rows give repeated results;
extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from html import escape, unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopline.session import cut

ROW, REMEMBERED = 64, 1_000_000
HOT, HOT_LEAST = 10_000, 200
SEQUENCE = "array<struct<pos:int,kind:string,text:string,digest:string>>"
_TAG = re.compile(r"<(?:!--.*?(?:--|$)|(/?)([a-zA-Z][a-zA-Z0-9]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*))>", re.S)
_ATTRIBUTE = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
_HIDDEN = {"script", "style", "head", "nav", "template"}
_HEAD_PARTS = {"head", "title", "meta", "link", "base", "script", "style", "noscript", "template"}
_MEDIA = {"img", "video", "audio"}
_BREAKS = {"p", "div", "br", "li", "tr", "h1", "h2", "h3", "h4", "h5", "h6", "article", "section", "figure", "table", "ul", "ol", "blockquote", "pre"}


def _ends(tags: list[re.Match]) -> dict[int, int]:
    """For each hidden element's opening tag the index of the tag that ends it; none for one that never ends."""
    closing: dict[str, int] = {}
    out, body = {}, None
    for k in range(len(tags) - 1, -1, -1):
        name = (tags[k][2] or "").lower()
        if tags[k][1]:
            closing[name] = k
        elif name in _HIDDEN:
            found = closing.get(name)
            if name == "head" and body is not None and (found is None or body < found):
                found = body - 1  # the body begins though the head was not closed
            if found is not None:
                out[k] = found
        if name and not tags[k][1] and name not in _HEAD_PARTS:
            body = k
    return out


def parse_sequence(html: str | None) -> list[dict]:
    """Ordered text runs and media references of one page; text keeps its characters, entities are resolved."""
    html = html or ""
    out: list[dict] = []
    run: list[str] = []
    caption: list[str] | None = None
    figures: list[tuple[list[dict], list[str]]] = []  # open figures: their media, their captions

    def flush() -> None:
        text = "".join(run)
        run.clear()
        if text.strip():
            out.append({"kind": "text", "text": text, "digest": None})

    def take(text: str) -> None:
        if text:
            (run if caption is None else caption).append(unescape(text) if "&" in text else text)

    def close_figure() -> None:
        media, captions = figures.pop()
        for x in media if captions else ():
            x["text"] = " ".join(captions)

    tags = list(_TAG.finditer(html))
    ends, at, skip = _ends(tags), 0, -1
    for k, m in enumerate(tags):
        if k <= skip:
            at = m.end()
            continue
        take(html[at : m.start()])
        at = m.end()
        closing, name = m[1], (m[2] or "").lower()
        if k in ends:
            skip = ends[k]
        elif name in _MEDIA and not closing:
            flush()
            found = {key.lower(): a or b or c or "" for key, a, b, c in _ATTRIBUTE.findall(m[3] or "")}
            out.append({"kind": "media", "text": unescape(found.get("alt", "")), "digest": found.get("data-digest") or "src:" + unescape(found.get("src", ""))})
            if figures:
                figures[-1][0].append(out[-1])
        elif name == "figcaption":
            if caption is not None and figures:
                figures[-1][1].append("".join(caption))
            caption = None if closing or not figures else []
        elif name in _BREAKS and caption is None:
            flush()
            if name == "figure" and not closing:
                figures.append(([], []))
            elif name == "figure" and figures:
                close_figure()
        elif name == "figure" and closing and figures:  # a caption that was never closed
            figures[-1][1].append("".join(caption or []))
            caption = None
            close_figure()
    take(html[at:])
    if caption and figures:
        figures[-1][1].append("".join(caption))
    while figures:
        close_figure()
    flush()
    return [{"pos": k} | x for k, x in enumerate(out)]


def _parsed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kind = pa.list_(pa.struct([("pos", pa.int32()), ("kind", pa.string()), ("text", pa.string()), ("digest", pa.string())]))
    for batch in batches:
        for at in range(0, batch.num_rows, 1024):
            part = batch.slice(at, 1024)
            rows = pa.array([parse_sequence(x) for x in part.column("html").to_pylist()], kind)
            yield pa.RecordBatch.from_arrays([part.column(k) for k in range(part.num_columns - 1)] + [rows], names=[*part.schema.names[:-1], "sequence"])


def sequences(pages: DataFrame, keys: list[str]) -> DataFrame:
    """``keys`` and the interleaved sequence of each row's ``html``."""
    schema = ", ".join(f"`{k}` {pages.schema[k].dataType.simpleString()}" for k in keys)
    return pages.select(*keys, "html").mapInArrow(_parsed, f"{schema}, sequence {SEQUENCE}")


def stored(raw: bytes) -> bytes:
    """A payload's stored form: zero bytes up to a positive multiple of 64, as a binary greymap 64 samples wide."""
    pad = -len(raw) % ROW if raw else ROW
    return b"P5\n%d %d\n255\n" % (ROW, (len(raw) + pad) // ROW) + raw + bytes(pad)


def _stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stored forms of the task's texts, each once."""
    seen: set[bytes] = set()
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            rows = []
            for raw in batch.column("text").slice(at, 256).cast(pa.large_binary()).to_pylist():
                name = hashlib.sha256(raw or b"").digest()
                if name not in seen:
                    if len(seen) >= REMEMBERED:  # then some are stored again, which costs space only
                        seen.clear()
                    seen.add(name)
                    rows.append(("sha256:" + name.hex(), len(raw or b""), stored(raw or b"")))
            names, sizes, media = zip(*rows, strict=True) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], names=["digest", "n_bytes", "media"])


def samples(media: Column) -> Column:
    """The samples of a container: what follows its header, whose second line holds width and height."""
    height = F.regexp_extract(F.decode(F.substring(media, 1, 40), "ISO-8859-1"), rf"^P5\n{ROW} (\d+)\n255\n", 1)
    return F.substring(media, F.length(height) + len(f"P5\n{ROW} \n255\n") + 1, 2**31 - 1)


def _measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Replaces the samples by a line of features."""
    for batch in batches:
        lines = []
        for cell in batch.column("data"):
            x = np.frombuffer(cell.as_buffer(), np.uint8) if cell.is_valid else np.zeros(0, np.uint8)
            count = np.bincount(x, minlength=256)
            share = count / max(1, len(x))
            mean = float(share @ np.arange(256))
            spread = float(np.sqrt(max(0.0, share @ np.arange(256) ** 2 - mean**2)))
            entropy = float(-(share[share > 0] * np.log2(share[share > 0])).sum())
            bands = "/".join(f"{v:.3f}" for v in share.reshape(8, 32).sum(axis=1))
            lines.append(f"rows={len(x) // ROW}|mean={mean:.3f}|spread={spread:.3f}|entropy={abs(entropy):.3f}|bands={bands}")
        at = batch.schema.get_field_index("data")
        yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(at)), pa.array(lines, pa.string())], names=[*batch.schema.names[:at], "measures"])


def features(store: DataFrame) -> DataFrame:
    """One row per digest, computed from the stored bytes."""
    data = samples(F.col("media"))
    cells = store.select("digest", "n_bytes", F.octet_length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"), data.alias("data"))
    size = F.octet_length("data").cast("long")
    row = cells.select("digest", "n_bytes", "media_bytes", "media_sha256", size.alias("payload_bytes"), F.sha2("data", 256).alias("payload_sha256"), F.crc32(F.substring("data", -ROW, ROW)).alias("tail_crc32"), "data")
    return row.mapInArrow(_measured, "digest string, n_bytes long, media_bytes long, media_sha256 string, payload_bytes long, payload_sha256 string, tail_crc32 long, measures string")


def resolve(sequence: DataFrame, keys: list[str], feats: DataFrame) -> DataFrame:
    """Every media reference with its position, caption and the features that its digest leads to. Payloads that very many
    references share (at most ``HOT``) are joined by broadcast, so their references don't meet in one task."""
    ref = cut(sequence.select(*keys, F.explode("sequence").alias("s")).where("s.kind = 'media'").select(*keys, "s.pos", F.col("s.text").alias("caption"), "s.digest"), "references")
    feats = cut(feats, "features")
    most = max(HOT_LEAST, ref.count() // HOT)
    hot = F.broadcast(cut(ref.groupBy("digest").agg(F.count("*").alias("n")).where(F.col("n") > most).select("digest"), "hot"))
    shared = ref.join(hot, "digest", "left_semi").join(F.broadcast(feats.join(hot, "digest", "left_semi")), "digest", "left")
    return ref.join(hot, "digest", "left_anti").join(feats, "digest", "left").unionByName(shared)


def _page(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts, names, sizes = (batch.column(k).to_pylist() for k in ("text", "digest", "n_bytes"))
        html = [f'<article><p>{escape(t or "", quote=False)}</p><figure><img data-digest="{d}"><figcaption>{n} bytes</figcaption></figure></article>' for t, d, n in zip(texts, names, sizes, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), pa.array(html, pa.large_string())], names=["doc_id", "n_bytes", "html"])


def document_media(docs: DataFrame) -> DataFrame:
    """Store every text as a payload, interleave it with its own page, and resolve the reference again.

    The store is written to shared storage and read back; all features come from the bytes that were read.
    """
    store = cut(docs.select("text").mapInArrow(_stored, "digest string, n_bytes long, media binary"), "media")
    n_bytes = F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes")
    digest = F.concat(F.lit("sha256:"), F.sha2(F.encode(F.coalesce("text", F.lit("")), "UTF-8"), 256))
    named = docs.select("doc_id", "text", n_bytes, digest.alias("digest"))
    pages = named.select("doc_id", "text", "digest", "n_bytes").mapInArrow(_page, "doc_id long, n_bytes long, html string")
    seq = sequences(pages, ["doc_id"]).select("doc_id", "sequence", F.size("sequence").alias("parts"))
    found = resolve(seq, ["doc_id", "parts"], features(store).dropDuplicates(["digest"]))
    shape = F.concat_ws("|", F.concat(F.lit("parts="), "parts"), F.concat(F.lit("media@"), "pos"), F.concat(F.lit("caption="), "caption"), "measures")
    return found.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", shape.alias("feature"))


def page_sequences(pages: DataFrame) -> DataFrame:
    """page_id, pos, kind, text, digest: the interleaved sequence of every page, one row an element."""
    return sequences(pages, ["page_id"]).select("page_id", F.explode("sequence").alias("s")).select("page_id", "s.pos", "s.kind", "s.text", "s.digest")

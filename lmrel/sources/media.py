"""Media as arguments: rows carry references, workers read the bytes only while a request is in flight."""

from __future__ import annotations

import json

from pyarrow import fs
from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("image", "audio", "video")


def media(uri: str | Column, kind: str, offset: str | Column | None = None, length: str | Column | None = None) -> Column:
    """A reference to a file, or to ``length`` bytes from ``offset`` of it; null where the uri is null.

    The reference is what is shuffled, keyed and deduplicated, so a file must not change while its
    answers are kept.
    """
    if kind not in KINDS:
        raise ValueError(f"kind is one of {KINDS}")
    at = lambda c: F.lit(None).cast("long") if c is None else (F.col(c) if isinstance(c, str) else c).cast("long")
    place = F.col(uri) if isinstance(uri, str) else uri
    return F.when(place.isNotNull(), F.struct(place.alias("media_uri"), F.lit(kind).alias("media_kind"), at(offset).alias("media_offset"), at(length).alias("media_length")))


def read(reference: dict) -> bytes:
    """The bytes of a reference, from any file system that Arrow knows; a plain path is a local or mounted file."""
    uri, offset, length = reference["media_uri"], reference["media_offset"] or 0, reference["media_length"]
    system, path = fs.FileSystem.from_uri(uri) if ":" in uri.split("/")[0] else (fs.LocalFileSystem(), uri)
    with system.open_input_file(path) as file:
        file.seek(offset)
        return file.read(length) if length is not None else file.read()


def references(inputs: str) -> list[dict]:
    """The references among a row's inputs (JSON)."""
    return [v for v in json.loads(inputs).values() if isinstance(v, dict) and "media_uri" in v] if '"media_uri"' in inputs else []


def loaded(inputs: tuple[str, ...]) -> tuple[tuple[str, bytes], ...]:
    """(kind, bytes) of all media of a request's rows, in their order."""
    return tuple((r["media_kind"], read(r)) for row in inputs for r in references(row))

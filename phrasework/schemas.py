"""Declared schemas; positions are 1-based, null references mark literals."""

from __future__ import annotations

STRINGS = "string_id string, text string"
CHARS = "string_id string, pos bigint, ch int"
SUFFIX = "string_id string, rank bigint, pos bigint, lcp bigint"
FACTOR = "string_id string, pos bigint, prev_len bigint, prev_ref bigint, next_len bigint, next_ref bigint"
CANDIDATES = "string_id string, i bigint, ord bigint, j bigint, lce bigint"
PHRASES = "string_id string, phrase_no int, start bigint, length bigint, ref bigint, literal string, side string"
REFGRAPH = "string_id string, pos bigint, target bigint, literal string"
COUNTS = "string_id string, n bigint, phrases bigint, literals bigint, copies bigint, left_refs bigint, right_refs bigint, seconds double, bytes bigint"
TRACE = "string_id string, phrase_no int, start bigint, length bigint, candidates bigint, groups bigint, tests bigint, finds bigint, unions bigint, stop_lce bigint"


def names(schema: str) -> list[str]:
    return [part.split()[0] for part in schema.split(", ")]

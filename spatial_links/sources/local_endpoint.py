"""A stand-in for a query endpoint, importable where there is no session: answers pages of a fixed set of squares, or what a query brings along."""

from __future__ import annotations

import json
import re

SQUARES = 250


def fetch(endpoint: str, text: str) -> str:
    words = text.split()
    limit, offset = int(words[-3]), int(words[-1])
    rows = ((f"urn:square:{i}", f"POLYGON (({i} 0, {i + 1} 0, {i + 1} 1, {i} 1, {i} 0))") for i in range(offset, min(offset + limit, SQUARES)))
    return json.dumps({"results": {"bindings": [{"s": {"value": u}, "wkt": {"value": w}} for u, w in rows]}})


def values(endpoint: str, text: str) -> str:
    """Answers a query whose VALUES block holds its data: (<uri> "wkt") pairs."""
    rows = re.findall(r'\(<([^>]*)> "([^"]*)"\)', text)
    return json.dumps({"results": {"bindings": [{"s": {"value": u}, "wkt": {"value": w}} for u, w in rows]}})

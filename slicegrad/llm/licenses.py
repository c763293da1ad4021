"""Licence scans: an Aho-Corasick automaton finds identifier tags and notice phrases in one pass; the expression
after a tag is parsed by a shunting-yard and evaluated.

Words are runs of a-z, 0-9 and characters beyond ASCII, after A-Z are lower-cased. A phrase is found where its words
stand consecutively, whatever stands between them. Each expression is evaluated to what it obliges to: ``and`` takes
the strictest of its sides, ``or`` the mildest, ``with`` makes its left side milder by an exception. An expression
that does not parse, or names what is no licence, gives no label of its own.

``score`` is the obligation of the whole text: 0 nothing found, 0.2 public domain, 0.4 permissive, 0.6 weak copyleft,
0.8 copyleft, 1 no right granted; a text with several findings has the largest. Null texts count as empty: no words,
no labels, score 0. Rows are independent, so repeated rows, null ids, ties and other columns need no care; an empty
table gives an empty result, and very long texts are scanned whole.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import process_cache, ship_by_value, text_or_empty

ship_by_value(__name__)

#: Fixed values of the contract: phrase and label.
BASE_PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Notice phrases of widely used licences, with the labels of this method.
NOTICE_PHRASES = {
    "mit license": "mit", "the mit licence": "mit", "permission is hereby granted free of charge": "mit",
    "apache license": "apache", "bsd license": "bsd", "redistribution and use in source and binary forms": "bsd",
    "mozilla public license": "mpl", "lesser general public license": "lgpl", "library general public license": "lgpl", "affero general public license": "agpl",
    "apache software license": "apache", "zlib license": "zlib", "boost software license": "bsl", "artistic license": "artistic", "academic free license": "afl",
    "open software license": "osl", "european union public licence": "eupl", "common development and distribution license": "cddl", "common public license": "cpl",
    "server side public license": "sspl", "business source license": "busl", "sil open font license": "ofl", "microsoft public license": "ms-pl",
    "creative commons zero": "cc0", "creative commons attribution sharealike": "cc-by-sa", "creative commons attribution noncommercial": "cc-by-nc",
    "this program is free software you can redistribute it": "gpl", "alle rechte vorbehalten": "reserved", "tous droits réservés": "reserved", "todos los derechos reservados": "reserved",
    "eclipse public license": "epl", "isc license": "isc", "unlicense": "unlicense", "cc0": "cc0", "public domain": "public-domain",
    "cc by nc": "cc-by-nc", "cc by sa": "cc-by-sa", "cc by nd": "cc-by-nd", "cc by nc sa": "cc-by-nc-sa", "cc by nc nd": "cc-by-nc-nd",
    "creative commons attribution": "cc-by", "creative commons": "creative-commons", "proprietary and confidential": "proprietary",
}
#: Obligation of a label's family, by the start of the label.
OBLIGATION = {
    "cc0": 0.2, "unlicense": 0.2, "public-domain": 0.2, "0bsd": 0.2,
    "mit": 0.4, "apache": 0.4, "bsl": 0.4, "artistic": 0.4, "afl": 0.4, "ofl": 0.4, "ms-pl": 0.4, "x11": 0.4, "python": 0.4, "psf": 0.4, "postgresql": 0.4, "ncsa": 0.4, "bsd": 0.4, "isc": 0.4, "zlib": 0.4, "cc-by": 0.4, "creative-commons": 0.4,
    "mpl": 0.6, "lgpl": 0.6, "epl": 0.6, "cc-by-sa": 0.6, "cddl": 0.6, "cpl": 0.6, "eupl": 0.6, "osl": 0.8, "gpl": 0.8, "agpl": 0.8, "gfdl": 0.8, "sspl": 0.8,
    "busl": 1.0, "licenseref": 0.5,
    "cc-by-nc": 1.0, "cc-by-nd": 1.0, "proprietary": 1.0, "reserved": 1.0,
}
TAG = "spdx license identifier"
_RUN = re.compile(rb"[^ ]+")
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+:-]*")
#: A-Z to a-z; the other ASCII characters but a-z and 0-9 to blanks.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))

#: Fixed precedence of the expression grammar, loosest first.
PRECEDENCE = {"or": 1, "and": 2, "with": 3}


def obligation(label: str) -> float | None:
    """By the family that the label begins with, alone or before a hyphen or digit; None if it is no licence's."""
    best = max((k for k in OBLIGATION if label.startswith(k) and not label[len(k) : len(k) + 1].isalpha()), key=len, default=None)
    return None if best is None else OBLIGATION[best]


def parse_expression(text: str) -> tuple[float, list[str]] | None:
    """(obligation, licence ids) of the expression that ``text`` begins with; None if it isn't one."""
    values: list[float] = []
    waiting: list[str] = []
    ids: list[str] = []

    def apply() -> bool:
        op = waiting.pop()
        if op == "(" or len(values) < 2:
            return False
        right, left = values.pop(), values.pop()
        values.append(max(left, right) if op == "and" else min(left, right) if op == "or" else max(0.0, left - 0.2))
        return True

    operand_next = True
    for word in (m.group().lower() for m in _TOKEN.finditer(text)):
        if word == "(" and operand_next:
            waiting.append(word)
        elif word in PRECEDENCE and not operand_next:
            while waiting and waiting[-1] != "(" and PRECEDENCE[waiting[-1]] >= PRECEDENCE[word]:
                if not apply():
                    return None
            waiting.append(word)
            operand_next = True
        elif word == ")" and not operand_next and "(" in waiting:
            while waiting[-1] != "(":
                if not apply():
                    return None
            waiting.pop()
        elif word not in PRECEDENCE and word not in "()" and operand_next:
            exception = bool(waiting) and waiting[-1] == "with"
            worth = 0.0 if exception else obligation(word.rstrip("+."))
            if worth is None:  # a word of the sentence, no licence
                return None
            values.append(worth)
            if not exception:
                ids.append(word)
            operand_next = False
        else:
            break  # what follows is no longer part of the expression
    if operand_next:
        return None
    while waiting:
        if not apply():
            return None
    return (values[0], ids) if len(values) == 1 else None


def automaton():
    """Phrases with a blank at either end, over text of the same form."""
    import ahocorasick

    out = ahocorasick.Automaton()
    for base, phrases in ((True, BASE_PHRASES), (False, NOTICE_PHRASES)):
        for phrase, label in phrases.items():
            own = f" {phrase} ".encode("utf-8").decode("latin-1")  # a character for each byte, as in the text
            out.add_word(own, (base, len(own), label))
    out.add_word(f" {TAG} ", (False, len(TAG) + 2, None))
    out.make_automaton()
    return out


def inner(spans: list[tuple[int, int]]) -> set[int]:
    """Numbers of the spans that lie inside a longer one."""
    out, reach = set(), -1
    for k in sorted(range(len(spans)), key=lambda k: (spans[k][0], -spans[k][1])):
        if spans[k][1] <= reach:
            out.add(k)
        reach = max(reach, spans[k][1])
    return out


def expressions(raw: bytes, after: list[int]) -> list[str]:
    """What follows the words of the given numbers, each up to the end of its line."""
    ends = [m.end() for m in _RUN.finditer(raw.translate(_FOLD))]
    lines = (raw[ends[k] :].split(b"\n", 1)[0].decode("utf-8", "replace") for k in after)
    return [line.split("\r")[0].lstrip(" \t").removeprefix(":").strip() for line in lines]


def scan(text: str | None, found=None) -> dict:
    found = found or automaton()
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.translate(_FOLD).split()
    line = (b" " + b" ".join(words) + b" ").decode("latin-1")
    base, labels, starts, score, tags = set(), set(), [], 0.0, []
    hits = [(end - length + 1, end, is_base, label) for end, (is_base, length, label) in found.iter(line)]
    hidden = inner([h[:2] for h in hits])
    seen, at = 0, 0
    for k, (start, end, is_base, label) in enumerate(hits):
        if label is not None:
            labels.add(label)
            if k not in hidden:  # of "lesser general public license" the whole says what is granted, not its end
                score = max(score, obligation(label))
        if is_base or label is None:
            # matches come by their ends; starts may step back by less than a phrase
            seen += line.count(" ", at, start) if start >= at else -line.count(" ", start, at)
            at = start
            if is_base:
                base.add(label)
                starts.append(seen)
            else:
                tags.append(seen + TAG.count(" "))
    for parsed in map(parse_expression, expressions(raw, tags) if tags else ()):
        if parsed is not None:
            score = max(score, parsed[0])
            labels.update(parsed[1])
    return {
        "n_words": len(words), "n_base": len(starts), "first_word": min(starts, default=None), "last_word": max(starts, default=None),
        "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(labels)), "score": float(score),
    }


FIELDS = {"n_words": "long", "n_base": "long", "first_word": "long", "last_word": "long", "base_labels": "string", "labels": "string", "score": "double"}


def _scanned():
    kinds = {"long": pa.int64(), "string": pa.string(), "double": pa.float64()}

    def run(batches):
        held = process_cache("licenses")
        found = held.get("found") or held.setdefault("found", automaton())
        for batch in batches:
            rows = [scan(t.as_py(), found) for t in batch.column("_text")]
            yield pa.RecordBatch.from_arrays([batch.column("_row"), *[pa.array([r[k] for r in rows], type=kinds[v]) for k, v in FIELDS.items()]], names=["_row", *FIELDS])

    return run


def license_scan(docs: DataFrame, text: str = "text", carry: list[str] | None = None) -> DataFrame:
    """The columns ``carry`` (all, if None) and the fields of the scan, which take the place of columns of those names."""
    from pyspark.sql import types as T

    carry = [c for c in (docs.columns if carry is None else carry) if c not in FIELDS]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in carry]).alias("_row"), text_or_empty(F.col(f"`{text}`")).alias("_text"))
    schema = T.StructType([T.StructField("_row", rows.schema["_row"].dataType), *T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in FIELDS.items())).fields])
    return rows.mapInArrow(_scanned(), schema).select(*[F.col("_row").getField(c).alias(c) for c in carry], *FIELDS)

"""Licence scans: one Aho-Corasick pass finds notice phrases and identifier tags, and a
shunting-yard parser evaluates the and/or/with expressions after a tag.

Texts are reduced to lower-case words joined by single spaces (only A-Z is lowered, a word is a
run of digits, letters and non-ASCII characters), so a phrase is a plain substring between
spaces.  Whole texts are scanned.

A tag's identifiers are labels if the public list has them (a prefix of it, `IDENTIFIERS`);
`expressions` holds the tags' expressions in normal form, and `permitted` says whether all of
them allow use by someone who accepts only `PERMISSIVE` licences (null without an expression).
Time and result grow in line with the text, however its expressions nest.  Null texts are empty: no words, no labels, score 0.  Rows are
independent, so repeated rows, ties, null ids and extra columns have no effect; an empty table
gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import slices, table

#: Phrases (as words) and the labels they prove.
BASE_PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}
#: Phrases of this operator's own: the label and how surely the phrase proves it.
PHRASES = {
    "permission is hereby granted free of charge to any person obtaining a copy": ("mit", 0.9),
    "licensed under the apache license": ("apache-2", 0.9),
    "gnu general public license": ("gpl", 0.8),
    "gnu lesser general public license": ("lgpl", 0.8),
    "gnu affero general public license": ("agpl", 0.8),
    "mozilla public license": ("mpl", 0.8),
    "bsd 3 clause": ("bsd-3-clause", 0.8),
    "bsd 2 clause": ("bsd-2-clause", 0.8),
    "redistribution and use in source and binary forms": ("bsd", 0.8),
    "creative commons attribution": ("cc-by", 0.7),
    "cc by sa": ("cc-by-sa", 0.8),
    "cc by nd": ("cc-by-nd", 0.8),
    "cc0 1 0 universal": ("cc0", 0.9),
    "dedicated to the public domain": ("public-domain", 0.7),
    "all rights reserved": ("all-rights-reserved", 0.4),
}
TAG = "spdx license identifier"
TAG_AT = re.compile(r"spdx-license-identifier\s*:\s*([^\n\r]*)", re.I)
TOKEN = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+:-]*")
#: Identifiers of the public licence list that a tag may name (in lower case; `+` may
#: follow, and any name may follow `licenseref-`), exceptions, and the licences that ask for
#: little but notice.
IDENTIFIERS = frozenset(
    """0bsd afl-3.0 agpl-1.0-only agpl-1.0-or-later agpl-3.0 agpl-3.0-only agpl-3.0-or-later apache-1.1 apache-2.0
    apsl-2.0 artistic-1.0 artistic-2.0 blueoak-1.0.0 bsd-1-clause bsd-2-clause bsd-2-clause-patent bsd-3-clause
    bsd-3-clause-clear bsd-4-clause bsl-1.0 busl-1.1 cc-by-3.0 cc-by-4.0 cc-by-nc-4.0 cc-by-nc-nd-4.0 cc-by-nc-sa-4.0
    cc-by-nd-4.0 cc-by-sa-3.0 cc-by-sa-4.0 cc0-1.0 cddl-1.0 cddl-1.1 cecill-2.1 cpal-1.0 cpl-1.0 ecl-2.0 epl-1.0 epl-2.0
    eupl-1.1 eupl-1.2 gfdl-1.3-only gfdl-1.3-or-later gpl-1.0-only gpl-1.0-or-later gpl-2.0 gpl-2.0-only
    gpl-2.0-or-later gpl-3.0 gpl-3.0-only gpl-3.0-or-later isc lgpl-2.0-only lgpl-2.0-or-later lgpl-2.1 lgpl-2.1-only
    lgpl-2.1-or-later lgpl-3.0 lgpl-3.0-only lgpl-3.0-or-later lppl-1.3c mit mit-0 mpl-1.1 mpl-2.0 ms-pl ms-rl mulanpsl-2.0
    ncsa odbl-1.0 ofl-1.1 openssl osl-3.0 postgresql psf-2.0 python-2.0 ruby sspl-1.0 unicode-3.0 unicode-dfs-2016
    unlicense upl-1.0 vim w3c wtfpl x11 zlib zpl-2.1""".split()
)
EXCEPTIONS = frozenset(
    """autoconf-exception-3.0 bison-exception-2.2 bootloader-exception classpath-exception-2.0 font-exception-2.0
    gcc-exception-2.0 gcc-exception-3.1 libtool-exception linux-syscall-note llvm-exception openjdk-assembly-exception-1.0
    qt-gpl-exception-1.0 u-boot-exception-2.0 wxwindows-exception-3.1""".split()
)
PERMISSIVE = frozenset("0bsd apache-2.0 bsd-2-clause bsd-3-clause bsl-1.0 cc0-1.0 isc mit mit-0 unlicense zlib".split())
#: How tightly the operators bind; `with` joins one licence and one exception before any of them.
BINDS = {"or": 1, "and": 2}


def known(name: str) -> bool:
    licence, _, exception = name.partition(" with ")
    return (licence.removesuffix("+") in IDENTIFIERS or licence.startswith("licenseref-")) and (not exception or exception in EXCEPTIONS)


def postfix(expression: str) -> tuple[list[str], list[str]] | None:
    """The expression's tokens with operators last (shunting-yard), and as they stood; None if it
    isn't well formed.  Reading stops where an expression can't go on, so a comment's end may
    follow it.  `with` takes a single licence on its left and a single exception on its right:
    together they are one operand, and anything else around it isn't well formed."""
    out: list[str] = []
    ops: list[str] = []
    told: list[str] = []
    want, depth, single = "operand", 0, False
    for m in TOKEN.finditer(expression):
        t = m[0]
        low = t.lower()
        word = t not in "()" and low not in BINDS and low != "with"
        if want == "exception":
            if not word:
                return None
            out[-1] = told[-1] = f"{out[-1]} with {low}"
            want, single = "operator", False
        elif t == "(" and want == "operand":
            ops.append(t)
            told.append(t)
            depth += 1
        elif t == ")" and want == "operator" and depth:
            while ops[-1] != "(":
                out.append(ops.pop())
            ops.pop()
            told.append(t)
            depth, single = depth - 1, False
        elif low in BINDS and want == "operator":
            while ops and ops[-1] != "(" and BINDS[ops[-1]] >= BINDS[low]:
                out.append(ops.pop())
            ops.append(low)
            told.append(low)
            want, single = "operand", False
        elif low == "with" and want == "operator":
            if not single:
                return None
            want = "exception"
        elif word and want == "operand":
            out.append(low)
            told.append(low)
            want, single = "operator", True
        else:
            break
    if want != "operator" or depth:
        return None
    return out + ops[::-1], told


def evaluate(tokens: list[str], allowed: frozenset[str] | None = None) -> tuple[frozenset[str], bool]:
    """The operands of an expression, and whether someone who accepts only `allowed` (None: all)
    may use the work: or needs one side, and needs both."""
    stack: list[bool] = []
    for t in tokens:
        if t not in BINDS:
            stack.append(allowed is None or t in allowed)
            continue
        b, a = stack.pop(), stack.pop()
        stack.append(a or b if t == "or" else a and b)
    return frozenset(t for t in tokens if t not in BINDS), stack[0]


_LOWER = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def normal(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_LOWER).split()


def automaton() -> ahocorasick.Automaton:
    found = ahocorasick.Automaton()
    for phrase in {*BASE_PHRASES, *PHRASES, TAG}:
        found.add_word(f" {phrase} ", phrase)
    found.make_automaton()
    return found


def scan(text: str | None, phrases: ahocorasick.Automaton) -> dict:
    """One text's row of `SCHEMA`."""
    words = normal(text or "")
    line = f" {b' '.join(words).decode('latin-1')} "
    starts, base, labels, score, tagged = [], set(), set(), 0.0, False
    expressions, permitted = [], None
    for end, phrase in phrases.iter(line):
        if phrase == TAG:
            tagged = True
            continue
        if phrase in BASE_PHRASES:
            starts.append(end - len(phrase) - 1)
            base.add(BASE_PHRASES[phrase])
            score = max(score, 0.9)
        if phrase in PHRASES:
            labels.add(PHRASES[phrase][0])
            score = max(score, PHRASES[phrase][1])
    if tagged:
        for m in TAG_AT.finditer(text):
            parsed = postfix(m[1])
            names = evaluate(parsed[0])[0] if parsed else frozenset()
            proven = {x for x in names if known(x)}
            if not proven:
                continue
            labels |= proven
            score = max(score, 1.0 if proven == names else 0.5)
            expressions.append(" ".join(parsed[1]).replace("( ", "(").replace(" )", ")"))
            permitted = (permitted is not False) and evaluate(parsed[0], PERMISSIVE)[1]
    first = line.count(" ", 0, min(starts) + 1) - 1 if starts else None
    last = first + line.count(" ", min(starts) + 1, max(starts) + 1) if starts else None
    return {"n_words": len(words), "n_base": len(starts), "first_word": first, "last_word": last, "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(base | labels)), "score": score, "expressions": "; ".join(expressions), "permitted": permitted}


SCHEMA = "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, expressions string, permitted boolean"


def scan_documents(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """`keep` columns and what `scan` finds, for every row."""
    schema = docs.select(*keep).schema
    for f in docs.sparkSession.createDataFrame([], SCHEMA).schema:
        schema = schema.add(f)
    kinds = {"n_words": pa.int64(), "n_base": pa.int64(), "first_word": pa.int64(), "last_word": pa.int64(), "base_labels": pa.string(), "labels": pa.string(), "score": pa.float64(), "expressions": pa.string(), "permitted": pa.bool_()}

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        phrases = automaton()
        for b in slices(batches, "_text"):
            found = [scan(t.as_py(), phrases) for t in b.column("_text")]
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keep))), *(pa.array([f[k] for f in found], v) for k, v in kinds.items())], [*keep, *kinds])

    return docs.select(*keep, docs[text].alias("_text")).mapInArrow(rows, schema)


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_documents(table(spark, sf_dir, "documents"), ["doc_id"])


QUERIES = {"op4_license_scan": op4_license_scan}
ORACLES: dict[str, str] = {}

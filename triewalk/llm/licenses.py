"""Licence scans: Aho-Corasick over a text's words finds notice phrases and identifier tags; the expression after a tag is read by
a shunting-yard parser with and, or and with."""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean

#: Phrases of the base: words in a row and their label.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Further notice phrases, the method's own; each gives a label and how sure it is.
NOTICES = {
    "gnu general public license version 3": ("gpl-3", 0.9),
    "gnu general public license version 2": ("gpl-2", 0.9),
    "gnu general public license": ("gpl", 0.6),
    "gnu lesser general public license": ("lgpl", 0.8),
    "gnu affero general public license": ("agpl", 0.8),
    "mozilla public license version 2": ("mpl-2", 0.9),
    "eclipse public license": ("epl", 0.8),
    "bsd 3 clause": ("bsd-3-clause", 0.8),
    "bsd 2 clause": ("bsd-2-clause", 0.8),
    "creative commons attribution": ("cc-by", 0.7),
    "cc by sa": ("cc-by-sa", 0.8),
    "cc by nc sa": ("cc-by-nc-sa", 0.8),
    "permission is hereby granted free of charge": ("mit", 0.8),
    "all rights reserved": ("all-rights-reserved", 0.5),
}
#: Words of an identifier tag, and identifiers whose label differs from their lower-case form.
TAG = "spdx license identifier"
IDENTIFIERS = {"apache-2.0": "apache-2", "gpl-2.0": "gpl-2", "gpl-2.0-only": "gpl-2", "gpl-2.0-or-later": "gpl-2", "gpl-3.0": "gpl-3", "gpl-3.0-only": "gpl-3", "gpl-3.0-or-later": "gpl-3", "mpl-2.0": "mpl-2", "cc-by-nc-4.0": "cc-by-nc", "cc-by-4.0": "cc-by", "cc-by-sa-4.0": "cc-by-sa"}

#: Identifiers that a tag may name, in lower case; any other word after a tag is no licence.
KNOWN = frozenset(
    """
    0bsd afl-3.0 agpl-1.0 agpl-3.0 agpl-3.0-only agpl-3.0-or-later apache-1.0 apache-1.1 apache-2.0 artistic-1.0 artistic-2.0 beerware
    blueoak-1.0.0 bsd-1-clause bsd-2-clause bsd-3-clause bsd-3-clause-clear bsd-4-clause bsl-1.0 busl-1.1 cc-by-3.0 cc-by-4.0
    cc-by-nc-3.0 cc-by-nc-4.0 cc-by-nc-nd-4.0 cc-by-nc-sa-4.0 cc-by-nd-4.0 cc-by-sa-3.0 cc-by-sa-4.0 cc0-1.0 cddl-1.0 cddl-1.1
    cecill-2.1 cpl-1.0 curl ecl-2.0 elastic-2.0 epl-1.0 epl-2.0 eupl-1.1 eupl-1.2 ftl gfdl-1.3 gpl-1.0 gpl-2.0 gpl-2.0-only
    gpl-2.0-or-later gpl-3.0 gpl-3.0-only gpl-3.0-or-later hpnd icu ijg isc json lgpl-2.0 lgpl-2.1 lgpl-2.1-only lgpl-2.1-or-later
    lgpl-3.0 lgpl-3.0-only lgpl-3.0-or-later libpng lppl-1.3c mit mit-0 mpl-1.1 mpl-2.0 ms-pl ms-rl mulanpsl-2.0 ncsa odbl-1.0
    ofl-1.1 openssl osl-3.0 php-3.01 postgresql psf-2.0 python-2.0 ruby sspl-1.0 unicode-dfs-2016 unlicense upl-1.0 vim w3c wtfpl
    x11 zlib zpl-2.1
    """.split()
)
#: Labels that an expression is evaluated against unless told otherwise.
PERMISSIVE = frozenset({"0bsd", "apache-2", "bsd-2-clause", "bsd-3-clause", "bsl-1.0", "cc0-1.0", "isc", "mit", "mit-0", "postgresql", "python-2.0", "unlicense", "zlib"})

_UPPER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Every byte outside words becomes a blank; letters A-Z become lower case.
_WORDS = bytes(32 if _UPPER[c] <= 0x2F or 0x3A <= _UPPER[c] <= 0x60 or 0x7B <= _UPPER[c] <= 0x7F else _UPPER[c] for c in range(256))
_TAGGED = re.compile(r"spdx-license-identifier:[ \t]*([^\r\n]*)", re.IGNORECASE)
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+-]*")
_BINDS = {"or": 1, "and": 2, "with": 3}


class BadExpression(ValueError):
    """A licence expression that cannot be read."""


def parse_expression(source: str) -> tuple:
    """The tree of a licence expression: ('id', name) or (operator, left, right); `with` binds closest, then `and`, then `or`."""
    values: list[tuple] = []
    waiting: list[str] = []

    def apply() -> None:
        op = waiting.pop()
        if op == "(" or len(values) < 2:
            raise BadExpression(source)
        right = values.pop()
        values.append((op, values.pop(), right))

    want_value = True
    for token in _TOKEN.findall(source):
        low = token.lower()
        if low in _BINDS:
            if want_value:
                raise BadExpression(source)
            while waiting and waiting[-1] != "(" and _BINDS[waiting[-1]] >= _BINDS[low]:
                apply()
            waiting.append(low)
            want_value = True
        elif token == "(":
            if not want_value:
                raise BadExpression(source)
            waiting.append(token)
        elif token == ")":
            if want_value:
                raise BadExpression(source)
            while waiting and waiting[-1] != "(":
                apply()
            if not waiting:
                raise BadExpression(source)
            waiting.pop()
        else:
            if not want_value:
                break  # the comment goes on after the expression
            values.append(("id", low))
            want_value = False
    if want_value:
        raise BadExpression(source)
    while waiting:
        apply()
    if len(values) != 1:
        raise BadExpression(source)
    return values[0]


def _nodes(tree: tuple) -> list[tuple]:
    """The nodes of an expression that count, each before its operands; the exception after `with` is no licence. Without recursion:
    a line of many operators makes a deep tree."""
    out, waiting = [], [tree]
    while waiting:
        node = waiting.pop()
        out.append(node)
        if node[0] != "id":
            waiting += node[1:2] if node[0] == "with" else node[1:]
    return out


def label_of(name: str) -> str | None:
    """The label of an identifier in lower case (`+`: or later); None for one that is not known."""
    name = name if name in KNOWN else name.removesuffix("+")
    return IDENTIFIERS.get(name, name) if name in KNOWN else None


def labels_of(tree: tuple) -> set[str]:
    """Labels of the known identifiers that an expression names."""
    return {label for node in _nodes(tree) if node[0] == "id" if (label := label_of(node[1]))}


def satisfied(tree: tuple, allowed: frozenset[str] | set[str]) -> bool:
    """Whether the allowed labels meet an expression: `or` leaves a choice, `and` needs both, `with` needs the licence before it.
    An unknown identifier is not allowed."""
    values: list[bool] = []
    for node in reversed(_nodes(tree)):
        if node[0] == "id":
            values.append(label_of(node[1]) in allowed)
        elif node[0] != "with":
            right, left = values.pop(), values.pop()
            values.append(left or right if node[0] == "or" else left and right)
    return values[0]


@lru_cache(maxsize=1)
def _automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for kind, phrases in (("base", {k: (v, 0.95) for k, v in BASE.items()}), ("notice", NOTICES), ("tag", {TAG: ("", 1.0)})):
        for phrase, (label, sure) in phrases.items():
            found.add_word(f" {phrase} ", (kind, phrase.count(" ") + 1, label, sure))
    found.make_automaton()
    return found


def scan(text: str | None) -> dict:
    """n_words, places (start word and label of each base phrase), labels of the base and of the method, score, expressions."""
    out = {"n_words": 0, "places": [], "base": set(), "own": set(), "score": 0.0, "expressions": []}
    if not text:
        return out
    words = text.encode("utf-8", "surrogatepass").translate(_WORDS).split()
    out["n_words"] = len(words)
    line = " " + b" ".join(words).decode("utf-8", "replace") + " "
    doubt, tagged, blanks, counted = 1.0, False, 0, 0
    for end, (kind, n, label, sure) in _automaton().iter(line):
        if kind == "tag":
            tagged = True
            continue
        doubt *= 1 - sure
        if kind == "base":
            # ends come in ascending order, so blanks are counted once; the phrase has one more than it has words
            blanks, counted = blanks + line.count(" ", counted, end + 1), end + 1
            out["places"].append((blanks - n - 1, label))
            out["base"].add(label)
        else:
            out["own"].add(label)
    if tagged:
        for m in _TAGGED.finditer(text):
            try:
                tree = parse_expression(m[1])
            except BadExpression:
                continue
            if named := labels_of(tree):
                out["expressions"].append(tree)
                out["own"] |= named
                doubt = 0.0
    out["score"] = 1 - doubt if out["base"] or out["own"] else 0.0
    return out


RESULT = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, permitted boolean"


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", allowed: frozenset[str] = PERMISSIVE) -> DataFrame:
    """One row a row of docs: words, places of base phrases, labels, and whether the allowed labels meet every expression after an
    identifier tag (null if there is none that names a known identifier). A null or empty text has no words and the score 0.

    Labels are distinct, sorted and comma-joined; those of the method include the base's. Every word of a text is read,
    however long. Other columns are not read; rows that repeat an id come back each. An empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                x = scan(text.as_py())
                at = [w for w, _ in x["places"]]
                rows.append((doc_id, x["n_words"], len(at), min(at, default=None), max(at, default=None), ",".join(sorted(x["base"])), ",".join(sorted(x["base"] | x["own"])), x["score"], all(satisfied(t, allowed) for t in x["expressions"]) if x["expressions"] else None))
            columns = list(zip(*rows, strict=True)) if rows else [()] * 9
            kinds = [*[pa.int64()] * 5, pa.string(), pa.string(), pa.float64(), pa.bool_()]
            yield pa.record_batch([pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in RESULT.split(", ")])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(lean(run), RESULT)

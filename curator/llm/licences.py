"""License detections by ordered signature rules.

A rule is a hand-written regex with a label, a priority and a confidence.  What any match must contain is read off the
parsed regex: groups of strings, of each of which one is there whichever alternatives match.  Only rules with a string
of each group in the lower-cased text are tried, so the gate drops no match.  Matches are taken by priority, longer first; a match inside an accepted one is suppressed ("GPL" within "LGPL v2.1 or later").
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from re import _parser as parser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.llm import flat

#: Phrases of consecutive words and their labels.
BASE_PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

_UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@dataclass(frozen=True)
class Rule:
    label: str
    pattern: str
    priority: int
    confidence: float


def _families() -> Iterator[Rule]:
    gap = r"[\s\-_,.:/()]*"
    licen = r"licen[cs]e"
    version = lambda v: rf"(?:version{gap}|v\.?{gap}|[\s\-_]+){re.escape(v)}(?:\.0)?(?![.\d]*\d)"
    # identifiers after a tag
    for name in (
        "MIT", "Apache-2.0", "Apache-1.1", "BSD-2-Clause", "BSD-3-Clause", "BSD-4-Clause", "0BSD", "ISC", "Zlib", "Unlicense", "WTFPL", "BSL-1.0", "MPL-1.1", "MPL-2.0", "EPL-1.0", "EPL-2.0",
        "CDDL-1.0", "CDDL-1.1", "GPL-1.0-only", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-2.0-only", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only",
        "LGPL-3.0-or-later", "AGPL-3.0-only", "AGPL-3.0-or-later", "Artistic-1.0", "Artistic-2.0", "EUPL-1.1", "EUPL-1.2", "OFL-1.1", "NCSA", "PostgreSQL", "Python-2.0", "PSF-2.0", "OpenSSL", "Ruby",
        "PHP-3.01", "Vim", "X11", "curl", "CC0-1.0", "CC-BY-3.0", "CC-BY-4.0", "CC-BY-SA-3.0", "CC-BY-SA-4.0", "CC-BY-NC-4.0", "CC-BY-ND-4.0", "CC-BY-NC-SA-4.0", "CC-BY-NC-ND-4.0", "MulanPSL-2.0",
        "UPL-1.0", "AFL-3.0", "OSL-3.0", "ECL-2.0", "MS-PL", "MS-RL", "Sleepycat", "LPPL-1.3c", "ODbL-1.0", "PDDL-1.0", "BUSL-1.1", "SSPL-1.0", "Elastic-2.0",
    ):
        yield Rule(name.lower(), rf"spdx-license-identifier:\s*{re.escape(name.lower())}(?![\w.+-])", 100, 0.99)
    # attribution licences: kinds in words and in letters, with and without a version
    kinds = {"by": "attribution", "by-sa": "attribution-sharealike", "by-nc": "attribution-noncommercial", "by-nd": "attribution-noderivatives", "by-nc-sa": "attribution-noncommercial-sharealike", "by-nc-nd": "attribution-noncommercial-noderivatives"}
    for kind, spelled in kinds.items():
        letters = gap.join(kind.split("-"))
        words = gap.join(w.replace("non", "non-?").replace("share", "share-?").replace("no", "no-?", w.startswith("noder")) for w in spelled.split("-"))
        end = r"(?![\s\-]*(?:sa|nc|nd)\b)"
        for v in ("1.0", "2.0", "2.5", "3.0", "4.0"):
            yield Rule(f"cc-{kind}-{v}", rf"\bcc{gap}{letters}{version(v.removesuffix('.0'))}", 80, 0.95)
            yield Rule(f"cc-{kind}-{v}", rf"\bcreative\s+commons\s+{words}(?:\s+(?:international|unported|generic))?{gap}{version(v.removesuffix('.0'))}", 85, 0.97)
        yield Rule(f"cc-{kind}", rf"\bcc{gap}{letters}\b{end}", 40, 0.8)
        yield Rule(f"cc-{kind}", rf"\bcreative\s+commons\s+{words}\b", 45, 0.85)
        yield Rule(f"cc-{kind}", rf"creativecommons\.org/licenses/{kind}/", 90, 0.98)
    yield Rule("cc0-1.0", rf"\bcc0{gap}(?:1(?:\.0)?\b)?", 60, 0.9)
    yield Rule("cc0-1.0", r"creativecommons\.org/publicdomain/zero/", 90, 0.98)
    # copyleft families: every version, alone, only, or later
    families = {"gpl": ("gpl", r"(?:gnu\s+)?general\s+public\s+" + licen), "lgpl": ("lgpl", r"(?:gnu\s+)?(?:lesser|library)\s+general\s+public\s+" + licen), "agpl": ("agpl", r"(?:gnu\s+)?affero\s+general\s+public\s+" + licen)}
    rank = {"gpl": 0, "lgpl": 3, "agpl": 3}
    for family, (short, title) in families.items():
        for v in ("1", "2", "2.1", "3"):
            later = r"(?:\s*\+|[\s,]*(?:or|and)\s+(?:\(at\s+your\s+option\)\s+)?any\s+later|[\s\-]*or[\s\-]+later)"
            for name in (rf"\b(?:gnu\s+)?{short}", rf"\b{title}"):
                yield Rule(f"{family}-{v}-or-later", rf"{name}{gap}{version(v)}{later}", 75 + rank[family], 0.97)
                yield Rule(f"{family}-{v}-only", rf"{name}{gap}{version(v)}[\s\-]*only\b", 74 + rank[family], 0.97)
                yield Rule(f"{family}-{v}", rf"{name}{gap}{version(v)}", 70 + rank[family], 0.93)
        yield Rule(family, rf"\b(?:gnu\s+)?{short}\b", 20 + rank[family], 0.6)
        yield Rule(family, rf"\b{title}\b", 25 + rank[family], 0.85)
    # permissive and other titles
    for label, title, versions in (
        ("apache", rf"\bapache(?:\s+software)?\s+{licen}", ("1.0", "1.1", "2.0")),
        ("mpl", rf"\bmozilla\s+public\s+{licen}", ("1.0", "1.1", "2.0")),
        ("epl", rf"\beclipse\s+public\s+{licen}", ("1.0", "2.0")),
        ("cddl", rf"\bcommon\s+development\s+and\s+distribution\s+{licen}", ("1.0", "1.1")),
        ("eupl", rf"\beuropean\s+union\s+public\s+{licen}", ("1.0", "1.1", "1.2")),
        ("artistic", rf"\bartistic\s+{licen}", ("1.0", "2.0")),
        ("bsl", rf"\bboost\s+software\s+{licen}", ("1.0",)),
        ("ofl", rf"\b(?:sil\s+)?open\s+font\s+{licen}", ("1.0", "1.1")),
        ("afl", rf"\bacademic\s+free\s+{licen}", ("2.1", "3.0")),
        ("osl", rf"\bopen\s+software\s+{licen}", ("2.1", "3.0")),
        ("psf", rf"\bpython\s+software\s+foundation\s+{licen}", ("2",)),
        ("php", rf"\bphp\s+{licen}", ("3.0", "3.01")),
        ("zpl", rf"\bzope\s+public\s+{licen}", ("2.0", "2.1")),
        ("ecl", rf"\beducational\s+community\s+{licen}", ("1.0", "2.0")),
        ("cpl", rf"\bcommon\s+public\s+{licen}", ("1.0",)),
        ("ibm-pl", rf"\bibm\s+public\s+{licen}", ("1.0",)),
        ("lppl", rf"\blatex\s+project\s+public\s+{licen}", ("1.2", "1.3c")),
        ("odbl", rf"\bopen\s+database\s+{licen}", ("1.0",)),
        ("busl", rf"\bbusiness\s+source\s+{licen}", ("1.1",)),
        ("sspl", rf"\bserver\s+side\s+public\s+{licen}", ("1",)),
    ):
        for v in versions:
            yield Rule(f"{label}-{v}", rf"{title}{gap}{version(v.removesuffix('.0'))}", 70, 0.95)
        yield Rule(label, rf"{title}\b", 30, 0.85)
    for label, pattern, confidence in (
        ("mit", rf"\b(?:the\s+)?(?:mit|expat)\s+{licen}\b", 0.9),
        ("mit", r"\bpermission\s+is\s+hereby\s+granted,?\s+free\s+of\s+charge,?\s+to\s+any\s+person\b", 0.95),
        ("apache-2.0", r"apache\.org/licenses/license-2\.0", 0.98),
        ("apache-2.0", r"\bapache[\s\-]2(?:\.0)?\b", 0.9),
        ("bsd-2-clause", rf"\b(?:2|two)[\s\-]clause\s+bsd\b|\bbsd[\s\-]2[\s\-]clause\b|\bsimplified\s+bsd\s+{licen}\b", 0.95),
        ("bsd-3-clause", rf"\b(?:3|three)[\s\-]clause\s+bsd\b|\bbsd[\s\-]3[\s\-]clause\b|\b(?:new|modified|revised)\s+bsd\s+{licen}\b", 0.95),
        ("bsd-4-clause", rf"\b(?:4|four)[\s\-]clause\s+bsd\b|\bbsd[\s\-]4[\s\-]clause\b|\boriginal\s+bsd\s+{licen}\b", 0.95),
        ("bsd", rf"\bbsd[\s\-](?:style\s+)?{licen}\b", 0.8),
        ("bsd", r"\bredistribution\s+and\s+use\s+in\s+source\s+and\s+binary\s+forms\b", 0.9),
        ("isc", rf"\bisc\s+{licen}\b", 0.9),
        ("isc", r"\bpermission\s+to\s+use,\s+copy,\s+modify,\s+and(?:/or)?\s+distribute\b", 0.85),
        ("zlib", rf"\bzlib(?:/libpng)?\s+{licen}\b", 0.9),
        ("unlicense", r"\bthe\s+unlicense\b|\bunlicense\.org\b", 0.9),
        ("unlicense", r"\bfree\s+and\s+unencumbered\s+software\s+released\s+into\s+the\s+public\s+domain\b", 0.97),
        ("wtfpl", r"\bwtfpl\b|\bdo\s+what\s+the\s+\S+\s+you\s+want\s+to\s+public\s+license\b", 0.9),
        ("openssl", rf"\bopenssl\s+{licen}\b", 0.9),
        ("ncsa", rf"\buniversity\s+of\s+illinois/?\s*ncsa\s+open\s+source\s+{licen}\b", 0.95),
        ("postgresql", rf"\bpostgresql\s+{licen}\b", 0.9),
        ("ms-pl", rf"\bmicrosoft\s+public\s+{licen}\b", 0.9),
        ("ms-rl", rf"\bmicrosoft\s+reciprocal\s+{licen}\b", 0.9),
        ("ms-eula", r"\bmicrosoft\s+software\s+license\s+terms\b", 0.8),
        ("upl", rf"\buniversal\s+permissive\s+{licen}\b", 0.9),
        ("elastic", rf"\belastic\s+{licen}(?:\s+2\.0)?\b", 0.85),
        ("sleepycat", rf"\bsleepycat\s+{licen}\b", 0.9),
        ("ruby", rf"\bruby\s+{licen}\b", 0.8),
        ("vim", rf"\bvim\s+{licen}\b", 0.8),
        ("x11", rf"\bx11\s+{licen}\b", 0.85),
        ("mulan", rf"\bmulan\s+permissive\s+software\s+{licen}\b", 0.95),
        ("public-domain", r"\b(?:in|into|to)\s+the\s+public\s+domain\b|\bpublic\s+domain\s+dedication\b", 0.7),
        ("gfdl", rf"\bgnu\s+free\s+documentation\s+{licen}\b|\bgfdl\b", 0.9),
        ("gfdl", rf"\bgnu\s+free\s+documentation\s+{licen}\b", 0.9),
        ("ogl", rf"\bopen\s+government\s+{licen}\b", 0.9),
        ("pddl", r"\bpublic\s+domain\s+dedication\s+and\s+license\b", 0.9),
        ("json", r"\bshall\s+be\s+used\s+for\s+good,\s+not\s+evil\b", 0.95),
        ("beerware", r"\bbeer-?ware\b", 0.8),
        ("proprietary", r"\bproprietary\s+and\s+confidential\b|\bconfidential\s+and\s+proprietary\b", 0.9),
        ("proprietary", r"\bunauthori[sz]ed\s+copying\s+of\s+this\s+file\b", 0.9),
        ("reserved", r"\ball\s+rights\s+reserved\b", 0.7),
        ("reserved", r"\balle\s+rechte\s+vorbehalten\b", 0.7),
        ("reserved", r"\btous\s+droits\s+réservés\b", 0.7),
        ("reserved", r"\btodos\s+los\s+derechos\s+reservados\b", 0.7),
        ("copyright", r"(?:©|\(c\)|\bcopyright\b)\s*(?:\(c\)\s*|©\s*)?(?:19|20)\d\d\b", 0.5),
        ("copyright", r"©\s*(?:19|20)\d\d\b", 0.5),
    ):
        yield Rule(label, pattern, 50, confidence)


@lru_cache(maxsize=1)
def rules() -> tuple[Rule, ...]:
    """All rules, best first."""
    return tuple(sorted(_families(), key=lambda r: (-r.priority, r.label, r.pattern)))


def _hash(text: str) -> np.ndarray:
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    return flat.Words(raw, np.array([0, len(raw)]), "alnum", True).hashes


def implied(tree) -> list[frozenset[str]]:
    """Groups of strings for a parsed regex: every match has at least one string of each group."""
    groups: list[frozenset[str]] = []
    run: list[str] = []

    def flush():
        if run:
            groups.append(frozenset(["".join(run)]))
            run.clear()

    for kind, value in tree:
        name = str(kind)
        if name == "LITERAL":
            run.append(chr(value))
        elif name not in ("AT", "ASSERT", "ASSERT_NOT"):  # those take no characters
            flush()
            if name == "SUBPATTERN":
                groups += implied(value[3])
            elif name in ("MAX_REPEAT", "MIN_REPEAT") and value[0] > 0:
                groups += implied(value[2])
            elif name == "BRANCH":
                ways = [implied(way) for way in value[1]]
                if all(ways):
                    groups.append(frozenset().union(*(max(way, key=_worth) for way in ways)))
    flush()
    return groups


def _worth(group: frozenset[str]) -> tuple[int, int]:
    return min(map(len, group)), -len(group)


@lru_cache(maxsize=1)
def _compiled():
    """Distinct strings, and each rule with its regex and its groups of places of strings; single letters tell little."""
    every = [(r, re.compile(r.pattern), [g for g in implied(parser.parse(r.pattern)) if _worth(g)[0] > 1 or not g.isdisjoint("©")]) for r in rules()]
    strings = sorted({x for _, _, groups in every for g in groups for x in g})
    of = {x: i for i, x in enumerate(strings)}
    return strings, [(r, regex, [frozenset(of[x] for x in g) for g in groups]) for r, regex, groups in every]


def detections(text: str, gated: bool = True) -> list[tuple[int, int, Rule]]:
    """Accepted matches (begin, end, rule) in a text; ``gated=False`` tries every rule."""
    strings, compiled = _compiled()
    low = text.translate(_UPPER)
    present = {i for i, x in enumerate(strings) if x in low} if gated else set()
    found = []
    for place, (rule, pattern, groups) in enumerate(compiled):
        if not gated or not any(g.isdisjoint(present) for g in groups):
            found += [(-rule.priority, m.start() - m.end(), m.start(), place, m.end(), rule) for m in pattern.finditer(low) if m.end() > m.start()]
    found.sort(key=lambda x: x[:4])
    taken: list[tuple[int, int, Rule]] = []
    for _, _, a, _, b, rule in found:
        if not any(x <= a and b <= y for x, y, _ in taken):
            taken.append((a, b, rule))
    return sorted(taken, key=lambda t: t[:2])


def _scan(with_spans: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        phrases = [(_hash(p), label) for p, label in BASE_PHRASES.items()]
        for batch in batches:
            texts = batch.column(1)
            for i, j, words in flat.word_runs(texts, "alnum", True):
                rows, h, owner = j - i, words.hashes, words.owners()
                n_base = np.zeros(rows, dtype=np.int64)
                least, most = np.full(rows, np.iinfo(np.int64).max), np.full(rows, -1)
                labels: list[set] = [set() for _ in range(rows)]
                for phrase, label in phrases:
                    m = len(h) - len(phrase) + 1
                    if m <= 0:
                        continue
                    at = np.flatnonzero(h[:m] == phrase[0])
                    for k in range(1, len(phrase)):
                        at = at[h[at + k] == phrase[k]]
                    at = at[owner[at] == owner[at + len(phrase) - 1]]
                    who = owner[at]
                    n_base += np.bincount(who, minlength=rows)
                    np.minimum.at(least, who, at - words.first[who])
                    np.maximum.at(most, who, at - words.first[who])
                    for d in np.unique(who).tolist():
                        labels[d].add(label)
                score, every, spans = [0.5 * (1 - 0.5 ** len(b)) for b in labels], [set(b) for b in labels], [[] for _ in labels]
                for d, text in enumerate(texts.slice(i, rows).to_pylist()):
                    got = detections(text) if text else []
                    best: dict[str, float] = {}
                    for a, b, rule in got:
                        best[rule.label] = max(best.get(rule.label, 0), rule.confidence)
                        spans[d].append({"first": a, "stop": b, "label": rule.label})
                    every[d] |= set(best)
                    if best:
                        score[d] = max(score[d], 1 - float(np.prod([1 - c for _, c in sorted(best.items())])))
                none = n_base == 0
                cols = [
                    batch.column(0).slice(i, rows), pa.array(words.counts.astype(np.int64)), pa.array(n_base), pa.array(least, mask=none), pa.array(most.astype(np.int64), mask=none),
                    pa.array([",".join(sorted(x)) for x in labels], pa.string()), pa.array([",".join(sorted(x)) for x in every], pa.string()), pa.array(score, pa.float64()),
                ]
                names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"]
                if with_spans:
                    cols.append(pa.array(spans, pa.list_(pa.struct([("first", pa.int32()), ("stop", pa.int32()), ("label", pa.string())]))))
                    names.append("spans")
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def license_scan(docs: DataFrame, with_spans: bool = True) -> DataFrame:
    """documents -> (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score[, spans]), map-only.

    Words are runs of letters, digits and non-ASCII characters, A-Z lowered.  Null reads as empty: no words, empty
    labels, null places, score 0.  Spans are character ranges of accepted detections.  Rows are scanned one by one,
    repeated ones alike; other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"
    return rows.mapInArrow(_scan(with_spans), schema + ", spans array<struct<first:int,stop:int,label:string>>" * with_spans)

"""Licence scans: sentences to known identifiers, sequences of identifiers to licences.

The lines of a paragraph are joined without their comment marks and normalised (lower case, plain quotes,
single spaces). A known sentence may begin and end wherever a sentence, a clause or a line does, and runs
over such places inside it; some hold slots (a year, a holder, a version). An open tail runs on to the end
of its sentence, that of a copyright or a tag to the end of its line, and never into the next known sentence.
The identifiers in reading order, without the sentences between that are not known, then meet the
ordered licence rules: the first rule that matches at a place wins and uses up its identifiers.
Identifiers no rule uses are reported as such.

Defined cases: null and empty texts have no sentences; a repeated sentence is reported each time;
repeated rows are scanned alike; an empty table gives no rows. Spans are those of the text as it came.
"""

from __future__ import annotations

import re
from bisect import bisect_right

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import bounded_batches, table

#: Known sentences, normalised. ``{v}`` is a version, ``{x}`` any words.
SENTENCES = {
    "copyright": "copyright {x}",
    "all-rights": "all rights reserved",
    "spdx": "spdx-license-identifier: {x}",
    "released-mit": "released under the mit license",
    "licensed-mit": "{w}licensed under the mit license",
    "mit-title": "the mit license{p}",
    "mit-grant": "permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files {x}",
    "mit-notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "as-is": "the software is provided as is, without warranty of any kind{x}",
    "no-liability": "in no event shall the authors or copyright holders be liable for any claim, damages or other liability{x}",
    "apache-under": "{a} under the apache license, version {v}{l}",
    "apache-may-not": "you may not use this file except in compliance with the license",
    "apache-copy": "you may obtain a copy of the license at{x}",
    "apache-as-is": "unless required by applicable law or agreed to in writing, software distributed under the license is distributed on an as is basis, without warranties or conditions of any kind{x}",
    "gpl-under": "this work is licensed under the gnu general public license, version {v}{o}",
    "gpl-free": "{s} is free software{c} you can redistribute it and/or modify it under the terms of the gnu general public license{n} as published by the free software foundation{x}",
    "gpl-hope": "{s} is distributed in the hope that it will be useful, but without any warranty{x}",
    "gpl-copy": "you should have received a copy of the gnu general public license{n} along with{x}",
    "lgpl-under": "{w}licensed under the gnu lesser general public license, version {v}{o}",
    "lgpl-free": "{s} is free software{c} you can redistribute it and/or modify it under the terms of the gnu lesser general public license{n} as published by the free software foundation{x}",
    "lgpl-copy": "you should have received a copy of the gnu lesser general public license{n} along with{x}",
    "mpl-terms": "this source code form is subject to the terms of the mozilla public license, v. {v}",
    "bsd-grant": "redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met{x}",
    "bsd-source": "redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer",
    "bsd-binary": "redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution",
    "bsd-endorse": "neither the name of {x} may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-as-is": "this software is provided by the copyright holders and contributors as is and any express or implied warranties{x} are disclaimed",
    "cc-by": "{w}licensed under cc by {v}",
    "cc-by-sa": "{w}licensed under cc by-sa {v}",
    "cc-by-nc": "{w}licensed under cc by-nc {v}",
    "cc-by-nc-sa": "{w}licensed under cc by-nc-sa {v}",
    "cc-by-nd": "{w}licensed under cc by-nd {v}",
    "cc0": "{w}(?:licensed under|dedicated to the public domain under) cc0{x}",
}

#: Licence rules in order; ``?`` marks an identifier that may be absent. Longer ones come first.
RULES = (
    ("MIT", ("mit-title?", "copyright?", "all-rights?", "mit-grant", "mit-notice", "as-is", "no-liability?")),
    ("BSD-3-Clause", ("copyright?", "all-rights?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse", "bsd-as-is?")),
    ("BSD-2-Clause", ("copyright?", "all-rights?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-as-is?")),
    ("Apache", ("copyright?", "apache-under", "apache-may-not?", "apache-copy?", "apache-as-is?")),
    ("GPL", ("copyright?", "gpl-free", "gpl-hope?", "gpl-copy?")),
    ("GPL", ("copyright?", "gpl-under")),
    ("LGPL", ("copyright?", "lgpl-free", "gpl-hope?", "lgpl-copy?")),
    ("LGPL", ("copyright?", "lgpl-under")),
    ("MPL", ("copyright?", "mpl-terms")),
    ("MIT", ("copyright?", "released-mit")),
    ("MIT", ("copyright?", "licensed-mit")),
    ("CC-BY-NC-SA", ("copyright?", "cc-by-nc-sa")),
    ("CC-BY-NC", ("copyright?", "cc-by-nc")),
    ("CC-BY-SA", ("copyright?", "cc-by-sa")),
    ("CC-BY-ND", ("copyright?", "cc-by-nd")),
    ("CC-BY", ("copyright?", "cc-by")),
    ("CC0", ("copyright?", "cc0")),
    ("named", ("copyright?", "spdx")),
    ("proprietary", ("copyright", "all-rights")),
)

SLOTS = {
    "v": r"(?P<v>\d+(?:\.\d+)*)", "x": r"(?P<x>.*?)", "w": r"(?:this (?:work|file|document|software) is )?", "p": r"(?: \(mit\))?",
    "a": r"(?:(?:this (?:work|file|document|software) is )?licensed|the asf licenses this file(?: to you)?)", "l": r"(?: \(the license\))?",
    "s": r"(?:this \w+|[\w+.-]+)", "c": r"[;:,.]?", "n": r"(?:,? version (?P<v>\d+(?:\.\d+)*),?)?", "o": r"(?:,? or (?:\(at your option\) )?(?:any )?later(?: version)?)?",
}
#: Every known sentence holds one of these words, so texts without them need no sentence work.
HINTS = ("licens", "copyright", "permission", "warrant", "redistribut", "reserved", "liab", "mozilla", "cc0")
#: Known sentences whose open tail ends with the line or clause.
OF_A_LINE = ("copyright", "spdx", "cc0")
MARKS = r"#*/\-;%>|•"
LINE_MARK = re.compile(rf"^(?:[{MARKS}]+|<!-*|\(\*+|dnl(?=\s)|rem(?=\s))+|(?<=\s)(?:[*/|#%;-]+>?|\*+\))\s*$", re.I)
MARK = re.compile(rf"^[{MARKS}]+")
ITEM = re.compile(r"\(?(?:\d{1,2}|[a-z]|[ivx]+)[.)]")
TAIL = "*/.;!|:?"
VERSION = re.compile(r"version (\d+(?:\.\d+)*)")
#: What follows "copyright" where a line merely wraps inside a sentence.
WRAPPED = re.compile(r"copyright (?:holders?|owners?|notices?|licen[cs]es?|statements?|laws?)\b")
#: How a word ends: inside a clause, a line, a clause, a sentence.
INSIDE, LINE, CLAUSE, COLON, SENTENCE = range(5)


def pattern(text: str) -> tuple[re.Pattern, bool]:
    """The pattern of a known sentence without its open tail, and whether it has one."""
    head = text.removesuffix("{x}")
    parts, used = [], set()
    for piece in re.split(r"(\{\w\})", head):
        if piece[:1] == "{":
            slot = SLOTS[piece[1]]
            parts.append(slot if piece not in used else re.sub(r"\?P<\w>", "?:", slot))
            used.add(piece)
        else:
            parts.append(piece if piece.startswith("(?:") else re.escape(piece))
    return re.compile("".join(parts), re.S), head != text


KNOWN = [(name, *pattern(text)) for name, text in SENTENCES.items()]


def plain(word: str) -> str:
    word = word.lower().replace("’", "'").replace("``", "").replace("''", "")
    return word.replace("“", "").replace("”", "").replace('"', "").replace("(c)", "©")


class Paragraph:
    """Normalised words of consecutive lines; for each where it may begin and end in the text, and how it ends."""

    def __init__(self):
        self.words, self.leads, self.ends, self.stops = [], [], [], []

    def add(self, text: str, start: int, end: int) -> bool:
        """Takes the line [start, end) over; False if it holds nothing but marks."""
        line, first = text[start:end], len(self.words)
        open_ = re.match(r"\s*", line).end()
        if m := LINE_MARK.match(line[open_:]):
            open_ += m.end()
        close = len(line)
        if m := LINE_MARK.search(line, open_):
            close = m.start() if m.start() > open_ else close
        lead = start
        for m in re.finditer(r"\S+", line[open_:close]):
            word, at = plain(m[0]), start + open_ + m.end()
            fresh = len(self.words) == first or self.stops[-1] != INSIDE
            if fresh:
                if ITEM.fullmatch(word):
                    if len(self.words) == first or self.stops[-1] == SENTENCE:
                        lead = at
                        continue
                word = MARK.sub("", word)
            if self.words and self.words[-1] == "copyright" and word[:1] == "©":
                word = word[1:]
            if not word:
                if self.words and len(self.words) > first and self.stops[-1] == INSIDE:
                    self.ends[-1] = at
                continue
            last = word.rstrip("')")[-1:]
            stop = INSIDE if word == "v." else SENTENCE if last in (".", "!", "?") else CLAUSE if last == ";" else COLON if last == ":" else INSIDE
            self.words.append(word)
            self.leads.append(lead)
            self.ends.append(at)
            self.stops.append(stop)
            lead = at
        if len(self.words) == first:
            return False
        if self.stops[-1] == INSIDE and self.words[-1] != "v.":
            self.stops[-1] = LINE
        if self.words[-1][-1] not in ".!?;":
            self.ends[-1] = end
        return True

    def found(self) -> list[tuple[str, str, int, int]]:
        """(identifier, version or words, start, end) of the known sentences, in order."""
        line = " ".join(self.words)
        if not any(hint in line for hint in HINTS):
            return []
        spots, at = [], 0
        for word in self.words:
            spots.append(at)
            at += len(word) + 1
        heads: dict[int, tuple | None] = {}

        def head(k: int) -> tuple | None:
            """The known sentence that begins at word k: its name, match, last word and whether its tail is open."""
            if k not in heads:
                heads[k] = None
                for name, known, tail in KNOWN:
                    m = known.match(line, spots[k])
                    if m is None or (tail and m.end() >= len(line) and line[m.end() - 1] == " "):
                        continue
                    if name == "copyright" and k and self.stops[k - 1] == LINE and WRAPPED.match(line, spots[k]):
                        continue
                    last = bisect_right(spots, m.end() if line[m.end() - 1] == " " else m.end() - 1) - 1
                    left = line[m.end() : spots[last] + len(self.words[last])]
                    if tail or (not left.strip(TAIL) and (self.stops[last] != INSIDE or last == len(self.words) - 1)):
                        heads[k] = name, m, last, tail
                        break
            return heads[k]

        out, k = [], 0
        while k < len(self.words):
            if (k and self.stops[k - 1] == INSIDE) or not (got := head(k)):
                k += 1
                continue
            name, m, last, tail = got
            if tail:
                ending = (LINE, CLAUSE, SENTENCE) if name in OF_A_LINE else (COLON, SENTENCE)
                while last + 1 < len(self.words) and self.stops[last] not in ending and (self.stops[last] == INSIDE or not head(last + 1)):
                    last += 1
            rest = line[m.end() : spots[last] + len(self.words[last])].strip(TAIL + " ")
            detail = m.groupdict().get("v") or ""
            if not detail and name in ("gpl-free", "lgpl-free"):
                detail = v[1] if (v := VERSION.search(rest)) else ""
            out.append((name, detail or (rest if tail and name != "copyright" else ""), self.leads[k], self.ends[last]))
            k = last + 1
        return out


def known_sentences(text: str) -> list[tuple[str, str, int, int]]:
    out, at, paragraph = [], 0, Paragraph()
    for line in text.split("\n"):
        if not paragraph.add(text, at, at + len(line)):
            out += paragraph.found()
            paragraph = Paragraph()
        at += len(line) + 1
    return out + paragraph.found()


def rule_end(ids: list[str], at: int, rule: tuple[str, ...]) -> int | None:
    """Where the rule's identifiers end if they begin at ``at``."""
    k = at
    for want in rule:
        if k < len(ids) and ids[k] == want.rstrip("?"):
            k += 1
        elif want[-1] != "?":
            return None
    return k if k > at else None


def licences(found: list[tuple[str, str]]) -> tuple[list[str], list[str]]:
    """Licences with their versions, in order, and the identifiers that no rule used."""
    ids, at, names, left = [f[0] for f in found], 0, [], []
    while at < len(ids):
        for name, rule in RULES:
            if (end := rule_end(ids, at, rule)) is not None:
                detail = next((v for _, v in found[at:end] if re.fullmatch(r"[\d.]+", v)), "")
                if name == "named":
                    name, detail = found[end - 1][1], ""
                names.append(f"{name}-{detail}" if detail else name)
                at = end
                break
        else:
            left.append(ids[at])
            at += 1
    return names, left


def scan(text: str | None) -> tuple[int, str, str, str, str]:
    found, spans = [], []
    text = text or ""
    lowered = text.lower()
    if any(hint in lowered for hint in HINTS):
        for name, detail, start, end in known_sentences(text):
            found.append((name, detail))
            spans.append(f"{name}:{start}:{end}")
    names, left = licences(found)
    return len(found), ",".join(f[0] for f in found), ",".join(names), ",".join(left), ",".join(spans)


RESULT = T.StructType([T.StructField("n_sentences", T.LongType()), *(T.StructField(n, T.StringType()) for n in ("sentence_ids", "licenses", "unmatched", "spans"))])


@F.pandas_udf(RESULT)
def licence_column(text: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([scan(t) for t in text], columns=RESULT.names)


def scan_licences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: known sentences, their identifiers, the licences they spell, what is left, spans."""
    bounded_batches(docs.sparkSession)
    return docs.select(F.col(id_col).alias("doc_id"), licence_column(F.col(text_col)).alias("s")).select("doc_id", "s.*")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licences(table(spark, sf_dir, "documents"))

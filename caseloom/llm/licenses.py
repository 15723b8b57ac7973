"""License scans (operator 5): ordered signature rules behind a keyword filter.

A text is folded (A-Z) and cut into words.  Rules are regular expressions over the words
joined by single spaces, with a keyword without which a rule can't match, a priority and a
confidence.  Of overlapping detections, one whose words lie inside those of a detection of
higher priority is suppressed.  The base phrases are counted at all their places and their
labels always stay.

Nulls: a null text is empty; a null doc_id stays null.  Repeated rows give repeated results,
an empty table an empty one.  Texts are read whole.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

# The base phrases and their labels.
BASE = ((b"mit license", "mit"), (b"apache license", "apache"), (b"general public license", "gpl"))
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")

# label | keyword | names | short identifiers, as they read once cut into words.
FAMILIES = """
mit | mit | mit license;mit licence;expat license;mit x11 license | mit;mit license
mit-0 | mit | mit no attribution(?: license)? | mit 0
apache-1.0 | apache | apache (?:software )?license(?: version)? 1 0 | apache 1 0
apache-1.1 | apache | apache (?:software )?license(?: version)? 1 1 | apache 1 1
apache-2.0 | apache | apache (?:software )?license(?: version)? 2(?: 0)? | apache 2(?: 0)?;asl 2(?: 0)?
gpl-1.0 | general public | (?:gnu )?general public licen[sc]e(?: as published by the free software foundation)?(?: either)?(?: version| v)? 1(?: 0)? | gpl v?1(?: 0)?(?: only| or later)?
gpl-2.0 | general public | (?:gnu )?general public licen[sc]e(?: as published by the free software foundation)?(?: either)?(?: version| v)? 2(?: 0)? | gpl v?2(?: 0)?(?: only| or later)?
gpl-3.0 | general public | (?:gnu )?general public licen[sc]e(?: as published by the free software foundation)?(?: either)?(?: version| v)? 3(?: 0)? | gpl v?3(?: 0)?(?: only| or later)?
lgpl-2.0 | general public | (?:gnu )?(?:lesser|library) general public licen[sc]e(?: version| v)? 2(?: 0)?(?! 1) | lgpl v?2(?: 0)?(?: only| or later)?
lgpl-2.1 | general public | (?:gnu )?(?:lesser|library) general public licen[sc]e(?: version| v)? 2 1 | lgpl v?2 1(?: only| or later)?
lgpl-3.0 | general public | (?:gnu )?lesser general public licen[sc]e(?: version| v)? 3(?: 0)? | lgpl v?3(?: 0)?(?: only| or later)?
agpl-3.0 | general public | (?:gnu )?affero general public licen[sc]e(?: version| v)? 3(?: 0)? | agpl v?3(?: 0)?(?: only| or later)?
gfdl-1.3 | documentation | (?:gnu )?free documentation licen[sc]e(?: version)?(?: 1 [123])? | gfdl(?: 1 [123])?
bsd-2-clause | bsd | (?:simplified bsd|bsd (?:2|two) clause|2 clause bsd)(?: license)? | bsd 2 clause
bsd-3-clause | bsd | (?:new bsd|modified bsd|revised bsd|bsd (?:3|three) clause|3 clause bsd)(?: license)? | bsd 3 clause
bsd-4-clause | bsd | (?:original bsd|bsd (?:4|four) clause|4 clause bsd)(?: license)? | bsd 4 clause
0bsd | bsd | (?:zero clause bsd|bsd zero clause)(?: license)? | 0bsd
mpl-1.1 | mozilla | mozilla public licen[sc]e(?: version| v)? 1 1 | mpl 1 1
mpl-2.0 | mozilla | mozilla public licen[sc]e(?: version| v)? 2(?: 0)? | mpl 2(?: 0)?
epl-1.0 | eclipse | eclipse public licen[sc]e(?: version| v)? 1(?: 0)? | epl 1 0
epl-2.0 | eclipse | eclipse public licen[sc]e(?: version| v)? 2(?: 0)? | epl 2 0
cddl-1.0 | common development | common development and distribution licen[sc]e(?: version)?(?: 1(?: 0)?)? | cddl(?: 1 0)?
cpl-1.0 | common public | common public licen[sc]e(?: version)?(?: 1(?: 0)?)? | cpl 1 0
cc0-1.0 | cc0 | cc0(?: universal)?(?: 1 0)?(?: universal)? | cc0 1 0
cc-by | cc by | cc by (?!nc|sa|nd)[1-4] [05] | cc by(?: [1-4] [05])?
cc-by-sa | cc by sa | cc by sa(?: [1-4] [05])? | cc by sa [1-4] [05]
cc-by-nc | cc by nc | cc by nc(?! sa| nd)(?: [1-4] [05])? | cc by nc [1-4] [05]
cc-by-nd | cc by nd | cc by nd(?: [1-4] [05])? | cc by nd [1-4] [05]
cc-by-nc-sa | cc by nc sa | cc by nc sa(?: [1-4] [05])? | cc by nc sa [1-4] [05]
cc-by-nc-nd | cc by nc nd | cc by nc nd(?: [1-4] [05])? | cc by nc nd [1-4] [05]
cc-by | creative commons | creative commons attribution(?! non| no| share)(?: [1-4] [05])?(?: international| unported| generic)? | cc by
cc-by-sa | creative commons | creative commons attribution share ?alike(?: [1-4] [05])? | cc by sa
cc-by-nc | creative commons | creative commons attribution non ?commercial(?! share| no)(?: [1-4] [05])? | cc by nc
cc-by-nc-sa | creative commons | creative commons attribution non ?commercial share ?alike(?: [1-4] [05])? | cc by nc sa
cc-by-nd | creative commons | creative commons attribution no ?deriv(?:ative)?s?(?: works)?(?: [1-4] [05])? | cc by nd
isc | isc | isc licen[sc]e | isc
zlib | zlib | zlib(?: libpng)? licen[sc]e | zlib
libpng | libpng | libpng licen[sc]e | libpng
bsl-1.0 | boost | boost software licen[sc]e(?: version)?(?: 1 0)? | bsl 1 0
artistic-1.0 | artistic | artistic licen[sc]e(?: version)? 1(?: 0)? | artistic 1 0
artistic-2.0 | artistic | artistic licen[sc]e(?: version)? 2(?: 0)? | artistic 2 0
unlicense | unlicense | the unlicense | unlicense
wtfpl | wtfpl | wtfpl | wtfpl
ms-pl | microsoft | microsoft public licen[sc]e | ms pl
ms-rl | microsoft | microsoft reciprocal licen[sc]e | ms rl
eupl-1.2 | european | european union public licen[sc]e(?: version| v)?(?: 1 [12])? | eupl 1 [12]
ofl-1.1 | open font | (?:sil )?open font licen[sc]e(?: version)?(?: 1 1)? | ofl 1 1
python-2.0 | python | python software foundation licen[sc]e(?: version)?(?: 2)? | psf 2 0
ruby | ruby | ruby licen[sc]e | ruby
php-3.01 | php | php licen[sc]e(?: version)?(?: 3 01)? | php 3 01
openssl | openssl | openssl licen[sc]e | openssl
postgresql | postgresql | postgresql licen[sc]e | postgresql
vim | vim | vim licen[sc]e | vim
curl | curl | curl licen[sc]e | curl
odbl-1.0 | open database | open database licen[sc]e(?: version)?(?: 1 0)? | odbl 1 0
odc-by | open data | open data commons attribution licen[sc]e | odc by 1 0
pddl-1.0 | public domain | public domain dedication and licen[sc]e | pddl 1 0
ogl | open government | open government licen[sc]e(?: version)?(?: [123] 0)? | ogl uk [123] 0
afl-3.0 | academic free | academic free licen[sc]e(?: version| v)?(?: 3 0)? | afl 3 0
osl-3.0 | open software | open software licen[sc]e(?: version| v)?(?: 3 0)? | osl 3 0
ecl-2.0 | educational | educational community licen[sc]e(?: version)?(?: 2 0)? | ecl 2 0
ncsa | ncsa | (?:university of illinois )?ncsa open source licen[sc]e | ncsa
upl-1.0 | universal permissive | universal permissive licen[sc]e(?: version)?(?: 1 0)? | upl 1 0
mulan-2.0 | mulan | mulan (?:psl|permissive software licen[sc]e)(?: v2)? | mulanpsl 2 0
sspl-1.0 | server side | server side public licen[sc]e(?: version| v)?(?: 1)? | sspl 1 0
busl-1.1 | business source | business source licen[sc]e(?: version)?(?: 1 1)? | busl 1 1
elastic-2.0 | elastic | elastic licen[sc]e(?: version)?(?: 2 0)? | elastic 2 0
blueoak-1.0.0 | blue oak | blue oak model licen[sc]e(?: 1 0 0)? | blueoak 1 0 0
openrail | openrail | openrail m? ?licen[sc]e | openrail
""".strip().splitlines()

#: What stands before a name where a text is put under a license.
GRANT = r"(?:(?:is |are )?(?:licensed|released|distributed|published|available|redistributed|covered|provided)(?: to you)? (?:under|by)|subject to|under the terms of|governed by)(?: the)?(?: terms of)?(?: the)?(?: gnu(?= ))?"
#: label, keyword, pattern: notices known by their own words.
NOTICES = (
    ("mit", "hereby granted", r"permission is hereby granted free of charge to any person obtaining a copy"),
    ("isc", "permission to use", r"permission to use copy modify and or distribute this software for any purpose"),
    ("bsd", "redistribution", r"redistributions? and use in source and binary forms with or without modification are permitted"),
    ("bsd-3-clause", "endorse", r"neither the name of .{0,80}? nor the names of its contributors may be used to endorse"),
    ("apache-2.0", "apache", r"you may not use this file except in compliance with the license"),
    ("gpl", "free software", r"this (?:program|library|file) is free software you can redistribute it and or modify"),
    ("zlib", "as is", r"this software is provided as is without any express or implied warranty in no event will the authors"),
    ("unlicense", "unencumbered", r"this is free and unencumbered software released into the public domain"),
    ("public-domain", "public domain", r"(?:released into|dedicated to|placed in|in) the public domain"),
    ("proprietary", "all rights reserved", r"all rights reserved"),
    ("proprietary", "confidential", r"confidential and proprietary"),
    ("cc", "creative commons", r"creative commons licen[sc]e"),
    ("wtfpl", "public license", r"do what the fuck you want to public license"),
    ("gpl", "general public", r"(?:gnu )?general public licen[sc]e"),
    ("lgpl", "general public", r"(?:lesser|library) general public licen[sc]e"),
    ("agpl", "general public", r"affero general public licen[sc]e"),
    ("apache", "apache", r"apache (?:software )?licen[sc]e"),
    ("bsd", "bsd", r"bsd (?:style )?licen[sc]e"),
    ("mpl", "mozilla", r"mozilla public licen[sc]e"),
    ("epl", "eclipse", r"eclipse public licen[sc]e"),
    ("artistic", "artistic", r"artistic licen[sc]e"),
)


@dataclass(frozen=True)
class Rule:
    label: str
    keyword: bytes
    pattern: re.Pattern
    priority: int
    confidence: float


@cache
def rules() -> tuple[Rule, ...]:
    """The rules in order; a smaller number is a higher priority."""
    out = []

    def add(label: str, keyword: str, pattern: str, priority: int, confidence: float) -> None:
        out.append(Rule(label, keyword.encode(), re.compile(rf"(?<![^ ])(?:{pattern})(?![^ ])".encode()), priority, confidence))

    for line in FAMILIES:
        label, keyword, names, ids = (x.strip() for x in line.split(" | "))
        for name in names.split(";"):
            add(label, keyword, f"{GRANT} (?:{name})", 1, 1.0)
            add(label, keyword, name, 3, 0.8)
        for x in ids.split(";"):
            add(label, "spdx", f"spdx license identifier (?:{x})", 0, 1.0)
            add(label, "licen", f"licen[sc]ed? (?:{x})(?: licen[sc]e)?", 4, 0.7)
    for label, keyword, pattern in NOTICES:
        add(label, keyword, pattern, 2 if len(pattern) > 45 else 5, 0.9 if len(pattern) > 45 else 0.6)
    return tuple(sorted(out, key=lambda r: r.priority))


#: Something of this stands in any folded text in which a rule or a base phrase can match.
_GATE = re.compile(rb"licen[sc]|spdx|(?<![a-z0-9])cc[^a-z0-9]+by(?![a-z])|cc0|wtfpl|creative[^a-z0-9]+commons|permission[^a-z0-9]+(?:is|to)|redistributions?[^a-z0-9]+and|bsd|rights[^a-z0-9]+reserved|confidential[^a-z0-9]+and|mit[^a-z0-9]+no|public[^a-z0-9]+domain|mulan|this[^a-z0-9]+(?:program|library|file|software|is)[^a-z0-9]+(?:is|provided|free)|neither[^a-z0-9]+the[^a-z0-9]+name")


def detect(text: bytes) -> tuple[list[tuple[int, int, str, int, float]], list[tuple[int, str]]]:
    """Detections that stand (first word, end word, label, priority, confidence) and the places of the base phrases."""
    joined = b" ".join(_WORD.findall(text.lower()))
    spaced = np.flatnonzero(np.frombuffer(joined, np.uint8) == 32)
    word = lambda at: int(np.searchsorted(spaced, at))
    padded, base = b" " + joined + b" ", []
    for phrase, label in BASE:
        i = padded.find(b" " + phrase + b" ")
        while i >= 0:
            base.append((word(i), label))
            i = padded.find(b" " + phrase + b" ", i + 1)
    found = []
    for r in rules():
        if r.keyword in joined:
            found += [(word(m.start()), word(m.end() - 1) + 1, r.label, r.priority, r.confidence) for m in r.pattern.finditer(joined)]
    found.sort(key=lambda x: (x[3], x[0] - x[1], x[0], x[2]))
    kept: list[tuple[int, int, str, int, float]] = []
    for d in found:
        if not any(k[0] <= d[0] and d[1] <= k[1] for k in kept):
            kept.append(d)
    return kept, sorted(base)


RESULT = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, detections array<struct<start:int,end:int,label:string>>"


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: word count, base phrases, labels and the detections that stand."""
    names = [f.split(" ")[0] for f in RESULT.split(", ")]
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("label", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = b.num_rows
            n_words, n_base, score = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n)
            first, last, base_labels, labels, told = [None] * n, [None] * n, [""] * n, [""] * n, [[]] * n
            for s in K.slices(b.column(1)):
                n_words[s.first : s.first + len(s)] = np.diff(K.words(s, K.ALNUM, hashed=False).doc)
                hits = [m.start() for m in _GATE.finditer(K.FOLD[s.raw].tobytes())]
                for k in sorted(set((np.searchsorted(s.at, hits, "right") - 1).tolist())) if hits else ():
                    kept, base = detect(s.text(k))
                    i = s.first + k
                    n_base[i] = len(base)
                    if base:
                        first[i], last[i] = base[0][0], base[-1][0]
                    own = {x[1] for x in base}
                    base_labels[i], labels[i] = ",".join(sorted(own)), ",".join(sorted(own | {d[2] for d in kept}))
                    score[i] = max([0.9 * bool(base), *(d[4] for d in kept)])
                    told[i] = [{"start": d[0], "end": d[1], "label": d[2]} for d in sorted(kept)]
            arrays = [b.column(0), pa.array(n_words), pa.array(n_base), pa.array(first, pa.int64()), pa.array(last, pa.int64()), pa.array(base_labels), pa.array(labels), pa.array(score), pa.array(told, kind)]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, RESULT)


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(K.table(spark, sf_dir, "documents"))

"""License scans by conditional compression.

Sentences with license words are joined into candidate blocks. Each block, and each of its sentences and lines, is compressed with zstandard,
plainly and with every template as a raw dictionary; the share of bytes that a template saves chooses the licenses and ranks them. Long
ones are compressed window by window, so that what is around a statement does not dilute it. What a template saves nothing of is none
of its license; the others are confirmed, best first, by exact differences of wording: the text must hold one of the template's statements
word for word (white space, marks and case aside) but for words that no license turns on, so a version or a clause that differs is another license.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

LEVEL = 3
#: Words of a window; statements have half as many at most, added words included.
WINDOW = 72
#: Words that make a sentence a candidate.
MARKER = r"(?i)licen[sc]|copyright|spdx|all rights reserved|public domain|redistribut|permission|warrant|\bCC[- ]?(?:BY|0)|\bA?L?GPL|\bunlicense"
SENTENCE_END = re.compile(r"(?<=[.!?;])\s+(?!\d)|\n+")
#: Where a single line end is white space, as statements are wrapped.
WRAPPED_END = re.compile(r"(?<=[.!?;])\s+(?!\d)|\n\s*\n")
WORD = re.compile(r"[A-Za-z]+|\d+(?:\.\d+)*")
#: Statements by which public licenses are named or given, by identifier.
STATEMENTS = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0", "Apache License Version 2.0", "SPDX-License-Identifier: Apache-2.0", "you may not use this file except in compliance with the License"],
    "MIT": ["Released under the MIT License", "Licensed under the MIT license", "The MIT License", "SPDX-License-Identifier: MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3", "GNU General Public License as published by the Free Software Foundation, either version 3 of the License", "SPDX-License-Identifier: GPL-3.0", "licensed under the GPL v3"],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2", "GNU General Public License as published by the Free Software Foundation, either version 2 of the License", "SPDX-License-Identifier: GPL-2.0"],
    "LGPL-3.0": ["This work is licensed under the GNU Lesser General Public License, version 3", "SPDX-License-Identifier: LGPL-3.0"],
    "LGPL-2.1": ["This work is licensed under the GNU Lesser General Public License, version 2.1", "SPDX-License-Identifier: LGPL-2.1"],
    "AGPL-3.0": ["This work is licensed under the GNU Affero General Public License, version 3", "SPDX-License-Identifier: AGPL-3.0"],
    "BSD-3-Clause": ["Licensed under the BSD 3-Clause License", "SPDX-License-Identifier: BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software"],
    "BSD-2-Clause": ["Licensed under the BSD 2-Clause License", "SPDX-License-Identifier: BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "ISC": ["Licensed under the ISC License", "SPDX-License-Identifier: ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "Mozilla Public License Version 2.0", "SPDX-License-Identifier: MPL-2.0"],
    "CC-BY-4.0": ["Licensed under CC BY 4.0", "licensed under a Creative Commons Attribution 4.0 International License"],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0", "licensed under a Creative Commons Attribution-ShareAlike 4.0 International License"],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0", "licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"],
    "CC-BY-ND-4.0": ["Licensed under CC BY-ND 4.0", "licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License"],
    "CC-BY-NC-SA-4.0": ["Licensed under CC BY-NC-SA 4.0", "licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License"],
    "CC0-1.0": ["CC0 1.0 Universal", "dedicated to the public domain under CC0 1.0"],
    "Unlicense": ["Released under the Unlicense", "This is free and unencumbered software released into the public domain"],
    "Proprietary": ["All rights reserved"],
}
#: Words that may be missing from or added to a statement without changing the license.
FREE = frozenset("a an and are as be by file files following for from in is it its of on or per program project released see software source that the these this to under with work works you your licensed license licence please code content document text page".split())


@dataclass(frozen=True)
class Template:
    name: str
    text: bytes
    statements: tuple[tuple[str, ...], ...]


def words(text: str) -> list[str]:
    return [w.lower().replace("licenc", "licens") for w in WORD.findall(text)]


@lru_cache(maxsize=1)
def _ready() -> list[tuple[Template, zstandard.ZstdCompressor]]:
    out = []
    for name, statements in STATEMENTS.items():
        text = " . ".join(" ".join(words(s)) for s in statements).encode()
        held = zstandard.ZstdCompressionDict(text, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        held.precompute_compress(level=LEVEL)
        out.append((Template(name, text, tuple(tuple(words(s)) for s in statements)), zstandard.ZstdCompressor(level=LEVEL, dict_data=held, write_checksum=False, write_content_size=False)))
    return out


def windows(told: list[str]) -> list[str]:
    """Words in windows that overlap by more than a statement with its added words."""
    if len(told) <= WINDOW:
        return [" ".join(told)]
    return list(dict.fromkeys(" ".join(told[at : at + WINDOW]) for at in range(0, len(told) - WINDOW // 2, WINDOW // 2)))


def reductions(block: str) -> list[tuple[float, str]]:
    """(share of compressed bytes saved, license), best first, ties by name; of a long block's windows the largest share. Compressed are words, as wording is compared."""
    plain, best = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False, write_content_size=False), {}
    for window in windows(words(block)):
        data = window.encode()
        size = len(plain.compress(data))
        for t, c in _ready():
            best[t.name] = max(best.get(t.name, -1.0), 1 - len(c.compress(data)) / size)
    return sorted(((r, name) for name, r in best.items()), key=lambda r: (-r[0], r[1]))


def differences(block: list[str], statement: tuple[str, ...], begins: frozenset[int] = frozenset()) -> Iterator[tuple[list[str], list[str], list[str]]]:
    """(matched, missing, added) words of the statement's places in the block: between its first and last matched words, in order. Lines begin at the words ``begins``."""
    n, m = len(block), len(statement)
    for start in (i for i in range(n) if block[i] == statement[0] or (m > 1 and block[i] == statement[1])):
        at, matched, missing, added = start, [], [], []
        for w in statement:
            near = next((j for j in range(at, min(n, at + 4)) if block[j] == w), None)
            if near is None:
                missing.append(w)
            else:
                added += block[at:near] if matched else []
                matched.append(w)
                at = near + 1
        tail = block[at : at + 1] if at not in begins else []  # what follows at once may go on with the name or version
        yield matched, missing, added + [w for w in tail if w in TURNING and w not in statement]


#: Words on which licenses turn: those of any statement that are not free.
TURNING = frozenset(w for s in STATEMENTS.values() for t in s for w in words(t)) - FREE | frozenset("nc nd sa lesser affero noncommercial noderivatives sharealike".split())


#: Words that tell that a name is a license's; a statement that has any must show one.
GIVING = frozenset("license licensed released under spdx".split())


def confirmed(block: str, among: list[str]) -> list[str]:
    """Licenses of ``among`` of which the block holds a statement, in that order."""
    told, begins = [], []
    for line in block.split("\n"):
        begins.append(len(told))
        told += words(line)
    known, lines = set(told), frozenset(begins)
    held = {t.name: t.statements for t, _ in _ready()}
    return [name for name in among if any(_holds(told, s, lines) for s in held[name] if known.issuperset(w for w in s if w not in FREE))]


def _holds(told: list[str], statement: tuple[str, ...], begins: frozenset[int]) -> bool:
    giving = GIVING.intersection(statement)
    return any(
        all(w in FREE for w in missing) and all(w not in TURNING for w in added) and len(added) <= 3 and len(missing) < len(statement) / 2 and (not giving or not giving.isdisjoint(matched))
        for matched, missing, added in differences(told, statement, begins)
    )


def blocks(text: str, sentence_end: re.Pattern[str] = SENTENCE_END) -> list[tuple[int, int]]:
    """Candidate blocks (start, end): runs of neighbouring sentences with license words."""
    out: list[tuple[int, int]] = []
    found = [m.start() for m in re.finditer(MARKER, text)]
    if not found:
        return out
    ends = [(m.start(), m.end()) for m in sentence_end.finditer(text)]
    starts = [0, *(e for _, e in ends)]
    stops = [*(s for s, _ in ends), len(text)]
    k = 0
    last = -2
    for at in found:
        while stops[k] <= at:
            k += 1
        if k == last:
            continue
        if k == last + 1 and out:
            out[-1] = (out[-1][0], stops[k])
        else:
            out.append((starts[k], stops[k]))
        last = k
    return out


def scan(text: str) -> list[dict]:
    """Licenses of a text, chosen by compression and confirmed by wording: start, end (code points of the block), license, reduction.

    What only the whole of wrapped sentences around a block confirms has their start and end.
    """
    out = []
    narrow, at = blocks(text), 0
    for a, b in blocks(text, WRAPPED_END):
        inner = []
        while at < len(narrow) and narrow[at][0] < b:
            inner.append(narrow[at])
            at += 1
        told: set[str] = set()
        for start, end in dict.fromkeys([*inner, (a, b)]):
            block = text[start:end]
            named: dict[str, float] = {}
            for part in dict.fromkeys([block, *SENTENCE_END.split(block), *WRAPPED_END.split(block)]):
                saved = {name: reduction for reduction, name in reductions(part) if reduction > 0 and name not in named}
                named |= {name: saved[name] for name in confirmed(part, list(saved))}
            if (start, end) not in inner:
                named = {n: r for n, r in named.items() if n not in told}
            told |= named.keys()
            out += [{"start": start, "end": end, "license": n, "reduction": r} for n, r in named.items()]
    return out


FOUND = "array<struct<start:int,end:int,license:string,reduction:double>>"
_TYPE = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("license", pa.string()), ("reduction", pa.float64())]))


def _scan(names: list[str]):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.num_columns - 1)
            found = [scan(t.as_py()) if t.is_valid else [] for t in texts]
            n = [len(blocks(t.as_py())) if t.is_valid else 0 for t in texts]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(n, pa.int32()), pa.array(found, _TYPE)], names=[*names, "n_blocks", "found"])

    return run


def scan_licenses(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """The ``keep`` columns with n_blocks (candidate blocks) and found (confirmed licenses) of every whole text.

    Texts without license words do not leave the JVM. Null and empty texts have no blocks; a block may name several
    licenses; repeated rows and null ids stay; an empty frame gives an empty one. Other columns are ignored.
    """
    text = F.col(text_col).cast("string")
    schema = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep) + f", n_blocks int, found {FOUND}"
    return docs.select(*keep, F.when(text.rlike(MARKER), text).alias("__text")).mapInArrow(_scan(list(keep)), schema)


def op1_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_licenses(table(spark, sf_dir, "documents", "doc_id", "text"))
    names = F.array_sort(F.array_distinct(F.transform("found", lambda x: x["license"])))
    spans = F.transform("found", lambda x: F.concat_ws(":", x["license"], x["start"].cast("string"), x["end"].cast("string")))
    best = F.array_max(F.transform("found", lambda x: F.struct(x["reduction"].alias("r"), x["license"].alias("l"))))
    return found.select("doc_id", F.col("n_blocks").cast("long").alias("n_blocks"), F.size(names).cast("long").alias("n_licenses"), F.concat_ws(",", names).alias("licenses"), F.concat_ws(",", spans).alias("spans"), best["l"].alias("best"), best["r"].alias("reduction"))

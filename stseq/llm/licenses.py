"""License scan: MinHash bands over overlapping windows retrieve templates, exact shingle containment verifies.

Texts and templates are reduced to lower-case letters and digits. A template of L words is looked for with
windows of 2*S shingles every S shingles, S the power of two of at least L (8 at least): one window holds it whole, at a
Jaccard similarity of about 1/4, and L/16 for those below 8 words (3/16 for the shortest). With ``BANDS`` bands of one
MinHash each, a window that holds a template collides with it with probability 1-(13/16)**BANDS or more, above 0.9999. A
hit counts if ``CONTAINMENT`` of the template's distinct 3-word shingles stand in the window, and all of those with a
number: a version is part of a license's name, so version 1 is not version 3.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.decontam import _CLEAN
from stseq.llm.textblock import Words, blocks, mix, shingle_hashes

SHINGLE, BANDS, CONTAINMENT = 3, 48, 0.8
#: License names and notices to look for.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License"),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-2.0", "it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License"),
    ("GPL-1.0", "This work is licensed under the GNU General Public License, version 1."),
    ("LGPL-2.0", "This work is licensed under the GNU Lesser General Public License, version 2."),
    ("LGPL-2.1", "This work is licensed under the GNU Lesser General Public License, version 2.1."),
    ("MPL-1.1", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 1.1."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("MIT", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)
_CLEAN_TABLE = np.frombuffer(_CLEAN, np.uint8)
_FACTORS = mix(np.arange(1, 4097, dtype=np.uint64)) | np.uint64(1)


class Templates:
    def __init__(self, templates=TEMPLATES, bands: int = BANDS):
        texts = pa.array([t.encode() for _, t in templates], pa.binary())
        self.names = [n for n, _ in templates]
        self.bands = bands
        self.shingles, self.size, self.step = [], [], []
        self.numbered = []  # shingles of each template that hold a number
        for _, _, data, offsets in blocks(texts):
            w = Words(_CLEAN_TABLE[data], offsets, lower=False)
            h, at = shingle_hashes(w.hashes(), w.first, SHINGLE)
            for i in range(len(offsets) - 1):
                self.shingles.append(np.unique(h[at[i] : at[i + 1]]))
                digit = np.array([bool(w.data[x:z].tobytes().isdigit()) for x, z in zip(w.starts[w.first[i] : w.first[i + 1]], w.ends[w.first[i] : w.first[i + 1]])])
                n = int(at[i + 1] - at[i])
                self.numbered.append(np.unique(h[at[i] : at[i + 1]][[bool(digit[k : k + SHINGLE].any()) for k in range(n)]]))
                self.size.append(int(at[i + 1] - at[i]))
                self.step.append(1 << max(3, int(np.ceil(np.log2(max(self.size[-1], 1))))))
        #: step -> for each band the sorted MinHashes and the template of each
        self.tables = {}
        for step in sorted(set(self.step)):
            own = [i for i, s in enumerate(self.step) if s == step]
            self.tables[step] = [
                (lambda m, o: (m[o], np.array(own)[o]))(m := np.array([(self.shingles[i] * f).min() for i in own]), np.argsort(m, kind="stable"))
                for f in _FACTORS[:bands]
            ]

    def scan(self, h: np.ndarray, at: np.ndarray, containment: float = CONTAINMENT) -> list[tuple[int, int, float, int, int]]:
        """(text, template, containment, first shingle in the text, matched span) of one block; ``at`` from shingle_hashes."""
        if not len(h):
            return []
        base = min(self.tables)
        n = np.diff(at)
        count = -(-n // base)  # base blocks of each text
        first = np.concatenate([[0], np.cumsum(count)])
        text = np.repeat(np.arange(len(n)), count)
        inside = np.arange(first[-1]) - first[:-1][text]
        begins = at[:-1][text] + inside * base
        found: set[tuple[int, int, int]] = set()
        for j in range(self.bands):
            low = np.minimum.reduceat(h * _FACTORS[j], begins)
            for step, table in self.tables.items():
                mins, owners = table[j]
                reach = step // base
                runs = np.flatnonzero(inside % reach == 0)
                part = np.minimum.reduceat(low, runs) if reach > 1 else low  # runs never cross texts: inside restarts at 0
                whose = text[runs]
                both = part.copy()
                same = whose[1:] == whose[:-1]
                both[:-1][same] = np.minimum(part[:-1], part[1:])[same]
                lo, hi = np.searchsorted(mins, both, "left"), np.searchsorted(mins, both, "right")
                for i in np.flatnonzero(hi > lo):
                    for o in owners[lo[i] : hi[i]]:
                        found.add((int(whose[i]), int(begins[runs[i]]), int(o)))
        out = []
        for t, begin, o in found:
            end = min(int(at[t + 1]), begin + 2 * self.step[o])
            hit = np.isin(h[begin:end], self.shingles[o])
            share = len(np.unique(h[begin:end][hit])) / len(self.shingles[o])
            if share >= containment and np.isin(self.numbered[o], h[begin:end]).all():
                spots = np.flatnonzero(hit)
                out.append((t, o, share, begin + int(spots[0]) - int(at[t]), int(spots[-1] - spots[0]) + SHINGLE))
        return out

    def settle(self, hits: list[tuple[int, int, float, int, int]]) -> list[tuple[int, int, float, int, int]]:
        """Of overlapping hits of one text only the best one stays: highest containment, then longest template."""
        kept: dict[int, list] = {}
        for hit in sorted(hits, key=lambda x: (x[0], -x[2], -self.size[x[1]], x[3], x[1])):
            have = kept.setdefault(hit[0], [])
            if all(hit[3] >= x[3] + x[4] or x[3] >= hit[3] + hit[4] for x in have):
                have.append(hit)
        return [h for k in sorted(kept) for h in sorted(kept[k], key=lambda x: x[3])]


def scan_licenses(docs: DataFrame, templates=TEMPLATES, containment: float = CONTAINMENT) -> DataFrame:
    """doc_id, license, containment, first_word, n_words: one row for each notice found in each row's whole text.

    ``first_word`` counts normalised words from 0. Null and empty texts hold none; repeated rows are reported each.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Templates(templates)
        for b in batches:
            rows = []
            for start, _, data, offsets in blocks(b.column(1)):
                w = Words(_CLEAN_TABLE[data], offsets, lower=False)
                h, at = shingle_hashes(w.hashes(), w.first, SHINGLE)
                for t, o, share, first, n in known.settle(known.scan(h, at, containment)):
                    rows.append((b.column(0)[start + t].as_py(), known.names[o], share, first, n))
            cols = list(zip(*rows)) if rows else [[]] * 5
            kinds = [b.schema.field(0).type, pa.string(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds)], names=["doc_id", "license", "containment", "first_word", "n_words"])

    return docs.select("doc_id", F.col("text").cast("binary")).mapInArrow(run, f"doc_id {kind}, license string, containment double, first_word bigint, n_words bigint")

"""License scan: fixed phrases, and an exact set-containment join of notice templates with text blocks.

Words are runs of digits, lower-cased letters and non-ASCII characters. A block is a line of a text, or
a paragraph: a run of lines between lines without words, so a notice wrapped over lines is scored as a whole. A template
matches a block when at least ``threshold`` of its distinct words are among the block's; whether its
distinctive words are all there is a flag beside the match. The join is exact: template words are put in one global order, rarest first, by the
number of documents that hold them (counted over all rows); a block that reaches the threshold must
hold one of a template's first few words (prefix filter), have enough words (length filter) and enough
ordered words left from the shared one on (position filter); the overlap of what remains is counted in full.

Phrases are counted wherever their words stand in a row, across lines too, overlaps included.

Odd input: null text is empty; texts without words have null places, empty labels and score 0; several
templates may match one block; a paragraph of one line is reported once, as a line; a null or repeated id keeps its rows; other columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hashed_texts, in_batches, lean, slices, word_hashes
from .decontaminate import _WORDS, document_frequency

#: Phrases and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    must: str


#: Notice templates of widely used public licenses: label, words, words that may not be missing.
TEMPLATES = (
    Template("mit", "released under the MIT license", "mit license"),
    Template("mit", "permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the software without restriction", "permission granted charge software"),
    Template("apache-2.0", "licensed under the Apache license, version 2.0", "apache license 2"),
    Template("apache-2.0", "licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License", "apache license compliance"),
    Template("gpl-3.0", "this work is licensed under the GNU general public license, version 3", "gnu public license 3"),
    Template("gpl-2.0", "this program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License; either version 2", "gnu public license 2"),
    Template("cc-by-nc", "licensed under CC BY-NC 4.0", "cc by nc"),
    Template("cc-by-sa", "licensed under CC BY-SA 4.0", "cc by sa"),
    Template("cc-by", "this work is licensed under a creative commons attribution 4.0 international license", "creative commons attribution"),
    Template("bsd", "redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "redistribution permitted conditions"),
    Template("mpl-2.0", "this source code form is subject to the terms of the Mozilla Public License, v. 2.0", "mozilla public license"),
)


def license_words(text: bytes) -> list[bytes]:
    return text.translate(_WORDS).split()


class ContainmentJoin:
    """Templates ready for the join; ``frequency`` gives the number of documents of each word (by hash)."""

    def __init__(self, templates, threshold: float, frequency: dict[int, int]):
        hashed = lambda text: word_hashes(b" ".join(license_words(text.encode()))).tolist()
        self.labels = [t.label for t in templates]
        self.sets = [frozenset(hashed(t.text)) for t in templates]
        self.musts = [frozenset(hashed(t.must)) for t in templates]
        vocabulary = sorted({w for s in self.sets for w in s}, key=lambda w: (frequency.get(w, 0), w))
        self.rank = {w: i for i, w in enumerate(vocabulary)}
        self.needs = [ceil(threshold * len(s) - 1e-9) for s in self.sets]
        self.index: dict[int, list] = {}
        for k, s in enumerate(self.sets):
            ordered = sorted(s, key=self.rank.__getitem__)
            for place, w in enumerate(ordered[: len(s) - self.needs[k] + 1]):
                self.index.setdefault(w, []).append((k, place))
        self.keys = np.array(sorted(self.index), np.uint64)

    def block(self, words: set[int]) -> list[tuple[int, float, bool]]:
        """(template, containment, all distinctive words there) of every template that the block reaches."""
        ordered = sorted(r for w in words if (r := self.rank.get(w)) is not None)
        tried, out = set(), []
        for w in words & self.index.keys():
            after = len(ordered) - int(np.searchsorted(ordered, self.rank[w]))
            for k, place in self.index[w]:
                need = self.needs[k]
                if k in tried or len(words) < need:
                    continue
                # words of a shared rank below this one would have been found by their own prefix entry
                if place + min(len(self.sets[k]) - place, after) < need:
                    continue
                tried.add(k)
                common = len(self.sets[k] & words)
                if common >= need:
                    out.append((k, common / len(self.sets[k]), self.musts[k] <= words))
        return out


def phrase_places(words: list[bytes], phrases: dict[bytes, str]) -> tuple[list[int], set]:
    joined = b" " + b" ".join(words) + b" "
    places, labels = [], set()
    for phrase, label in phrases.items():
        at = joined.find(phrase)
        while at >= 0:
            places.append(joined.count(b" ", 0, at))
            labels.add(label)
            at = joined.find(phrase, at + 1)
    return places, labels


RESULT = "struct<n_words:bigint,n_base:bigint,first_word:bigint,last_word:bigint,base_labels:string,labels:string,score:double,matches:array<struct<label:string,line:bigint,containment:double>>,block_labels:string,blocks:array<struct<label:string,first_line:bigint,last_line:bigint,containment:double,distinctive:boolean>>>"


def scan(docs: DataFrame, text_col: str = "text", templates=TEMPLATES, threshold: float = 0.85, column: str = "license") -> DataFrame:
    """The rows with a struct of counts, labels and score.

    ``blocks`` and ``block_labels`` have every line and paragraph that reaches the threshold (label, lines from 0, containment,
    whether the distinctive words are there); ``matches`` and ``labels`` those lines among them that hold the distinctive words.
    """
    vocabulary = np.unique(word_hashes(b" ".join(w for t in templates for w in license_words(t.text.encode()))))
    seen, _ = document_frequency(docs, vocabulary, text_col)
    join = ContainmentJoin(templates, threshold, dict(zip(vocabulary.tolist(), seen.tolist())))
    phrases = {b" " + p.encode() + b" ": label for p, label in PHRASES.items()}

    def one(text: bytes, words: list[bytes], hot: bool):
        places, base = phrase_places(words, phrases)
        blocks = []
        if hot:
            lines = [set(word_hashes(b" ".join(found)).tolist()) if (found := license_words(line)) else set() for line in text.split(b"\n")]
            begin = 0
            for number, held in enumerate([*lines, set()]):
                if held:
                    blocks += [(k, number, number, share, sure) for k, share, sure in join.block(held)]
                    continue
                if number - begin > 1:
                    blocks += [(k, begin, number - 1, share, sure) for k, share, sure in join.block(set().union(*lines[begin:number]))]
                begin = number + 1
        blocks.sort(key=lambda m: (m[1], m[2], m[0]))
        matches = [m for m in blocks if m[1] == m[2] and m[4]]
        labels, block_labels = (base | {join.labels[m[0]] for m in some} for some in (matches, blocks))
        score = 1.0 if base else max((m[3] for m in blocks), default=0.0)
        return {
            "n_words": len(words), "n_base": len(places), "first_word": min(places, default=None), "last_word": max(places, default=None),
            "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(labels)), "score": score,
            "matches": [{"label": join.labels[k], "line": a, "containment": s} for k, a, _, s, _ in matches], "block_labels": ",".join(sorted(block_labels)),
            "blocks": [{"label": join.labels[k], "first_line": a, "last_line": b, "containment": s, "distinctive": sure} for k, a, b, s, sure in blocks],
        }

    kind = pa.struct([(n, pa.int64()) for n in ("n_words", "n_base", "first_word", "last_word")] + [("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("matches", pa.list_(pa.struct([("label", pa.string()), ("line", pa.int64()), ("containment", pa.float64())]))), ("block_labels", pa.string()), ("blocks", pa.list_(pa.struct([("label", pa.string()), ("first_line", pa.int64()), ("last_line", pa.int64()), ("containment", pa.float64()), ("distinctive", pa.bool_())])))])

    @F.arrow_udf(RESULT)
    @lean()
    def judge(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for array in arrays:
            texts = [t or b"" for t in array.cast(pa.binary()).to_pylist()]
            out = []
            for lo, hi in slices([len(t) for t in texts], 1 << 19):
                parts = [license_words(t) for t in texts[lo:hi]]
                h, ends = hashed_texts([b" ".join(p) for p in parts])
                sums = np.concatenate(([0], np.cumsum(np.isin(h, join.keys))))
                out += [one(t, p, sums[b] > sums[a]) for t, p, a, b in zip(texts[lo:hi], parts, ends, ends[1:])]
            yield pa.array(out, kind)

    return in_batches(docs).withColumn(column, judge(F.col(text_col).cast("string")))


def op4_license_scan(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    sure = F.expr("array_join(array_sort(array_distinct(transform(filter(license.blocks, b -> b.distinctive), b -> b.label))), ',')")
    names = ("n_words", "n_base", "first_word", "last_word", "base_labels")
    return scan(docs).select("doc_id", *[f"license.{n}" for n in names], F.col("license.block_labels").alias("labels"), "license.score", sure.alias("distinctive_labels"))

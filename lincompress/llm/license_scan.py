"""License scans with a positional index of licence words.

Every occurrence of a licence word votes, through the postings (template, position) of that word, for a template and the place
where its first word would stand. All licence words vote, however common, so the votes for a place are the template's words
that stand there, and nothing has to be counted over the corpus. A place counts if enough of the template's words stand in
place and its mandatory phrase stands there as a whole; the score is the best share at places with two words or more.

Words are the runs of ASCII letters and digits and of all characters beyond ASCII, with A-Z in lower case.

Edge cases: a null text is empty; repeated rows get a row each; an empty table gives an empty result; a document without
licence words has no labels and score 0. Other columns are never looked at.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import read

# Base phrases with labels, then templates as (label, text, mandatory phrase); public licence wordings.
PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
TEMPLATES = (
    ("mit", "released under the mit license", "mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted free of charge"),
    ("apache-2.0", "licensed under the apache license version 2 0", "apache license version 2 0"),
    ("apache-2.0", "you may not use this file except in compliance with the license you may obtain a copy of the license at", "except in compliance with the license"),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    ("gpl-3.0", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3", "gnu general public license"),
    ("gpl-2.0", "this program is licensed under the gnu general public license version 2", "gnu general public license version 2"),
    ("lgpl", "licensed under the gnu lesser general public license", "lesser general public license"),
    ("agpl", "licensed under the gnu affero general public license", "affero general public license"),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", "cc by nc 4 0"),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", "cc by sa 4 0"),
    ("cc-by-4.0", "this work is licensed under a creative commons attribution 4 0 international license", "creative commons attribution 4 0"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license v 2 0"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "with or without fee is hereby granted"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "released into the public domain"),
    ("reserved", "all rights reserved", "all rights reserved"),
)
#: Share of a template's words that must stand in place.
SHARE = 0.7
_GAPS = bytes(c if chr(c).isalnum() and c < 128 or c >= 128 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").lower().translate(_GAPS).split()


class Scanner:
    def __init__(self, templates=TEMPLATES, share: float = SHARE):
        self.templates = [(label, [w.encode() for w in text.split()], [w.encode() for w in phrase.split()]) for label, text, phrase in templates]
        self.share = share
        self.postings: dict[bytes, list[tuple[int, int]]] = defaultdict(list)
        for t, (_, words, _) in enumerate(self.templates):
            for j, w in enumerate(words):
                self.postings[w].append((t, j))
        self.phrases = [(b" " + p.encode() + b" ", label) for p, label in PHRASES]

    def base(self, words: list[bytes]) -> tuple[list[int], set[str]]:
        """Starts of the base phrases, and their labels."""
        line = b" " + b" ".join(words) + b" "
        starts, labels = [], set()
        for phrase, label in self.phrases:
            at = line.find(phrase)
            place = done = 0
            while at >= 0:
                place += line.count(b" ", done, at + 1)
                done = at + 1
                starts.append(place - 1)
                labels.add(label)
                at = line.find(phrase, at + 1)
        return starts, labels

    def aligned(self, words: list[bytes]) -> tuple[set[str], float]:
        """Labels of verified templates, and the best share of a template's words in place."""
        votes: Counter = Counter()
        for i, w in enumerate(words):
            if w in self.postings:
                for t, j in self.postings[w]:
                    votes[t, i - j] += 1
        labels, best = set(), 0.0
        for (t, at), n in votes.items():
            if n < 2:
                continue
            label, template, phrase = self.templates[t]
            placed = n / len(template)
            best = max(best, placed)
            if placed >= self.share and label not in labels:
                there = words[max(at, 0) : at + len(template)]
                if any(there[k : k + len(phrase)] == phrase for k in range(len(there) - len(phrase) + 1)):
                    labels.add(label)
        return labels, best


RESULT = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def scan(docs: DataFrame, templates=TEMPLATES) -> DataFrame:
    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates)
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                words = words_of(text.as_py())
                starts, base = scanner.base(words)
                labels, score = scanner.aligned(words)
                row = (i, len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(base | labels)), score)
                for column, x in zip(out, row, strict=True):
                    column.append(x)
            kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(out, kinds, strict=True)], names=[x.split()[0] for x in RESULT.split(", ")])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(each, RESULT)


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read(spark, sf_dir, "documents"))

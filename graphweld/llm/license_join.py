"""License scans as an exact set-similarity join of text blocks with templates.

A block is a window of a text's words that slides over line ends; it is as long
as the template with its repeated words, and a quarter longer to allow for
insertions. A template is a set of words, some of them obligatory: the words
that tell one license from another. Words of decoration (comment signs) are
none, so wrapped and commented statements are found. A block meets a template
if it holds at least ``threshold`` of the template's words, all obligatory ones
among them. Where blocks of several templates overlap, a template gives way to
one that demands all of its obligatory words and more, so a statement gets its
most specific label.

The words of the templates are ordered by how many texts of the whole corpus
hold them, rarest first. A block that meets the threshold must hold one of the
first ``n - ceil(threshold * n) + 1`` words (prefix filter), must have at least
``ceil(threshold * n)`` words (length filter), and after the first hit at
position ``i`` the words from ``i`` on must still suffice (positional filter).
Windows around places that pass are verified by counting while they slide, so
the join is exact.

Templates are a parameter of the program and travel with the tasks. Corpus
frequencies are counted in a first pass over all texts and add up to one row a
template word. No document is shuffled.

The base labels are places of fixed phrases, over the words of the whole text.
Defined results: a null or empty text has no words, no labels and score 0.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import map_slices

#: Phrases with their base labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: License statements that the method looks for, by label; a word with a star is obligatory.
TEMPLATES = {
    "apache-2.0": ["licensed under the apache* license version 2* 0", "you may obtain a copy of the license at http www apache* org licenses license 2* 0"],
    "mit": ["released under the mit* license", "licensed under the mit* license", "permission* is hereby granted free of charge to any person obtaining a copy of this software* and associated documentation files to deal in the software without restriction"],
    "gpl": ["licensed under the gnu* general* public* license* version", "this program is free software you can redistribute it and or modify it under the terms of the gnu* general* public* license*"],
    "lgpl": ["gnu* lesser* general* public* license* as published by the free software foundation", "licensed under the gnu* lesser* general* public* license* version"],
    "agpl": ["gnu* affero* general* public* license* as published by the free software foundation", "licensed under the gnu* affero* general* public* license* version"],
    "bsd": ["released under the bsd* license", "licensed under the bsd* license", "redistribution* and use in source and binary* forms with or without modification are permitted provided that the following conditions are met"],
    "mpl-2.0": ["this source code form is subject to the terms of the mozilla* public license v 2* 0"],
    "cc-by": ["licensed under a creative* commons* attribution* license", "this work is licensed under cc* by* 4 0", "available under cc* by* 4 0"],
    "cc-by-nc": ["licensed under cc* by* nc* 4 0", "licensed under a creative* commons* attribution* noncommercial* license"],
    "cc-by-sa": ["licensed under cc* by* sa* 4 0", "licensed under a creative* commons* attribution* sharealike* license"],
    "cc-by-nd": ["licensed under cc* by* nd* 4 0", "licensed under a creative* commons* attribution* noderivatives* license"],
    "cc-by-nc-sa": ["licensed under cc* by* nc* sa* 4 0", "licensed under a creative* commons* attribution* noncommercial* sharealike* license"],
    "cc-by-nc-nd": ["licensed under cc* by* nc* nd* 4 0", "licensed under a creative* commons* attribution* noncommercial* noderivatives* license"],
    "cc0": ["dedicated to the public domain under cc0*"],
}
THRESHOLD = 0.8

#: Word bytes are digits, letters and everything outside ASCII; A-Z are lower-cased.
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def phrase_places(flat: bytes, phrases: list[tuple[bytes, str]]) -> list[tuple[int, int, str]]:
    """(first word, last word, label) of each place. flat: the words, a space before each and after the last."""
    found = []
    for phrase, label in phrases:
        wide = b" " + phrase + b" "
        at = flat.find(wide)
        words = 0
        mark = 0
        while at >= 0:
            words += flat.count(b" ", mark, at)
            mark = at
            found.append((words, words + phrase.count(b" "), label))
            at = flat.find(wide, at + 1)
    return found


def words_of(text: bytes) -> list[bytes]:
    """The words of a text, lower-cased."""
    return text.translate(_TABLE).split()


@dataclass(frozen=True)
class Template:
    label: str
    tokens: list[bytes]  # distinct words in corpus order
    need: int  # how many of them a block must hold
    must: frozenset[bytes]  # obligatory ones
    span: int  # words of a block


def compile_templates(templates: dict[str, list[str]], counts: dict[bytes, int], threshold: float) -> tuple[list[Template], dict]:
    """Templates with words in corpus order, and the inverted index of their prefixes."""
    ready, index = [], {}
    for label, texts in templates.items():
        for text in texts:
            words = text.split()
            tokens = sorted({w.rstrip("*").encode() for w in words}, key=lambda w: (counts.get(w, 0), w))
            need = math.ceil(threshold * len(tokens) - 1e-9)
            for i, w in enumerate(tokens[: len(tokens) - need + 1]):
                index.setdefault(w, []).append((len(ready), i))
            ready.append(Template(label, tokens, need, frozenset(w[:-1].encode() for w in words if w.endswith("*")), math.ceil(len(words) / threshold - 1e-9)))
    return ready, index


Hit = tuple[int, int, int, float]  # template, first and last word of the overlapping blocks that meet it, best containment


def join_windows(words: list[bytes], ready: list[Template], index: dict) -> list[Hit]:
    """Every run of overlapping blocks that meet a template."""
    seen: dict[int, dict[int, int]] = {}
    for at, w in enumerate(words):
        for t, i in index.get(w, ()):
            seen.setdefault(t, {})[at] = i
    found: list[Hit] = []
    for t, places in seen.items():
        q = ready[t]
        vocabulary = frozenset(q.tokens)
        ordered = sorted(places)
        k = 0
        while k < len(ordered):
            # one run of places whose windows touch
            first = last = ordered[k]
            least = places[first]
            while k < len(ordered) and ordered[k] - last < q.span:
                last = ordered[k]
                least = min(least, places[last])
                k += 1
            low, high = max(0, first - q.span + 1), min(len(words), last + q.span)
            if high - low < q.need or len(q.tokens) - least < q.need:
                continue
            held: Counter = Counter()
            for at in range(low, high):
                if words[at] in vocabulary:
                    held[words[at]] += 1
                out = at - q.span
                if out >= low and words[out] in vocabulary:
                    held[words[out]] -= 1
                    if not held[words[out]]:
                        del held[words[out]]
                if len(held) >= q.need and held.keys() >= q.must:
                    start, score = max(low, at - q.span + 1), len(held) / len(q.tokens)
                    if found and found[-1][0] == t and start <= found[-1][2]:
                        found[-1] = (t, found[-1][1], at, max(score, found[-1][3]))
                    else:
                        found.append((t, start, at, score))
    return found


def most_specific(hits: list[Hit], ready: list[Template]) -> list[Hit]:
    """The hits without those that overlap one of a template with more obligatory words."""
    return [h for h in hits if not any(ready[h[0]].must < ready[g[0]].must and g[1] <= h[2] and h[1] <= g[2] for g in hits)]


def word_counts(documents: DataFrame, templates: dict[str, list[str]] = TEMPLATES) -> dict[bytes, int]:
    """How many texts of the whole corpus hold each template word. One row a word reaches the driver."""
    vocabulary = frozenset(w.rstrip("*").encode() for texts in templates.values() for t in texts for w in t.split())

    def make():
        def work(part):
            total: Counter = Counter()
            for text in part.column("body").to_pylist():
                if text:
                    total.update(vocabulary.intersection(words_of(text)))
            return {"word": list(total), "n": list(total.values())}

        return work

    body = documents.select(F.col("text").cast("binary").alias("body"))
    rows = map_slices(body, "body", make, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    return {bytes(r.word): r.n for r in rows}


def scan(documents: DataFrame, templates: dict[str, list[str]] = TEMPLATES, phrases: dict[str, str] = PHRASES, threshold: float = THRESHOLD) -> DataFrame:
    """Words, base places and labels of every document, the method's labels, its best containment and the number of its statements: separate runs of blocks that meet a template."""
    ready, index = compile_templates(templates, word_counts(documents, templates), threshold)
    base = [(p.encode(), label) for p, label in phrases.items()]
    rare = frozenset(index)

    def make():
        def work(part):
            out: dict[str, list] = {k: [] for k in ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "n_blocks")}
            for text in part.column("body").to_pylist():
                words = words_of(text or b"")
                places = []
                if any(p in (flat := b" " + b" ".join(words) + b" ") for p, _ in base):
                    places = phrase_places(flat, base)
                hits = [] if rare.isdisjoint(words) else most_specific(join_windows(words, ready, index), ready)
                own = {x[2] for x in places}
                row = (
                    len(words),
                    len(places),
                    min((x[0] for x in places), default=None),
                    max((x[0] for x in places), default=None),
                    ",".join(sorted(own)),
                    ",".join(sorted(own | {ready[h[0]].label for h in hits})),
                    1.0 if places else max((h[3] for h in hits), default=0.0),
                    len(hits),
                )
                for k, v in zip(out, row, strict=True):
                    out[k].append(v)
            return out | {"doc_id": part.column("doc_id")}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    source = documents.select("doc_id", F.col("text").cast("binary").alias("body"))
    return map_slices(source, "body", make, f"doc_id {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, n_blocks long")

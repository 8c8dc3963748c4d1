"""Licence scan: a generalised suffix automaton of licence words, fed with the words of each file.

Every template (and every phrase, itself a short template) is inserted, word by word, into one automaton.
A text is streamed through it once: after each word the state and the matched length are the matching
statistics, the longest stretch that ends here and occurs in some template; the suffix links say how much of it ends in
every other template. A phrase ends here exactly when its own state is on those links. The maximal matches of each template
are chained (in order, small gaps) into spans; a template whose words are covered enough gives its label, and so does the name
of a licence.

Nulls count as empty texts, empty texts have no words, repeated rows give repeated results, further columns of
the input are not looked at, an empty table gives an empty result. Long texts are streamed: memory is their words.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Phrases that always count, with their labels.
BASE = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

# Notices of well-known public licences, in lower case.
TEMPLATES = {
    "mit": [
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
        "released under the mit license",
    ],
    "apache": [
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0",
        "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
        "licensed under the apache license version 2 0",
    ],
    "gpl": [
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
        "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details",
        "this work is licensed under the gnu general public license version 3",
    ],
    "lgpl": ["this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation"],
    "agpl": ["it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version"],
    "bsd": ["redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"],
    "isc": ["permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies"],
    "mpl": ["this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0"],
    "cc-by": ["this work is licensed under a creative commons attribution 4 0 international license"],
    "cc-by-sa": ["this work is licensed under a creative commons attribution sharealike 4 0 international license"],
    "cc-by-nc": ["this work is licensed under a creative commons attribution noncommercial 4 0 international license", "licensed under cc by nc 4 0"],
    "unlicense": ["this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software"],
}

# Names and identifiers of licences, with their labels; they count beside the base phrases, not as base.
NAMES = {
    "mozilla public license": "mpl",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "bsd license": "bsd",
    "bsd 2 clause": "bsd",
    "bsd 3 clause": "bsd",
    "isc license": "isc",
    "eclipse public license": "epl",
    "boost software license": "bsl",
    "creative commons attribution": "cc-by",
    "creative commons attribution sharealike": "cc-by-sa",
    "creative commons attribution noncommercial": "cc-by-nc",
    "cc by sa": "cc-by-sa",
    "cc by nc": "cc-by-nc",
    "cc by nd": "cc-by-nd",
    "cc0 1 0": "cc0",
    "the unlicense": "unlicense",
    "spdx license identifier mit": "mit",
    "spdx license identifier apache 2 0": "apache",
    "spdx license identifier gpl 2 0": "gpl",
    "spdx license identifier gpl 3 0": "gpl",
    "spdx license identifier lgpl": "lgpl",
    "spdx license identifier agpl": "agpl",
    "spdx license identifier mpl 2 0": "mpl",
    "spdx license identifier isc": "isc",
}

#: Bytes of words stay (A-Z as a-z), all others separate words.
_TO_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_TO_WORDS).split() if text else []


class Automaton:
    """Generalised suffix automaton over words, with the templates that each state occurs in and where."""

    def __init__(self, templates: list[list[bytes]], phrases: list[list[bytes]]):
        self.next: list[dict] = [{}]
        self.link, self.length = [-1], [0]
        ends: list[dict[int, set]] = [{}]  # template -> where in it the state's stretch ends
        for t, words in enumerate(templates):
            last = 0
            for pos, w in enumerate(words):
                last = self._extend(last, w, ends)
                ends[last].setdefault(t, set()).add(pos)
        by_length = sorted(range(1, len(self.next)), key=self.length.__getitem__)
        for v in reversed(by_length):
            for t, pos in ends[v].items():
                ends[self.link[v]].setdefault(t, set()).update(pos)
        self.ends = [{t: sorted(pos) for t, pos in e.items()} for e in ends]
        #: template -> the state of the longest end of this state's stretch that occurs in the template
        self.deepest: list[dict[int, int]] = [{}] * len(self.next)
        for v in by_length:
            self.deepest[v] = self.deepest[self.link[v]] | dict.fromkeys(ends[v], v)
        own = {}
        for k, words in enumerate(phrases):
            v = 0
            for w in words:
                v = self.next[v][w]
            own[v] = (*own.get(v, ()), (k, len(words)))
        #: phrases that end wherever the state is reached with at least their length
        self.phrases: list[tuple] = [()] * len(self.next)
        for v in by_length:
            self.phrases[v] = own.get(v, ()) + self.phrases[self.link[v]]

    def _extend(self, last: int, w: bytes, ends: list) -> int:
        def clone(p: int, q: int) -> int:
            c = len(self.next)
            self.next.append(dict(self.next[q]))
            self.link.append(self.link[q])
            self.length.append(self.length[p] + 1)
            ends.append({})
            self.link[q] = c
            while p >= 0 and self.next[p].get(w) == q:
                self.next[p][w] = c
                p = self.link[p]
            return c

        if w in self.next[last]:  # the stretch is known from an earlier template
            q = self.next[last][w]
            return q if self.length[q] == self.length[last] + 1 else clone(last, q)
        v = len(self.next)
        self.next.append({})
        self.length.append(self.length[last] + 1)
        self.link.append(0)
        ends.append({})
        p = last
        while p >= 0 and w not in self.next[p]:
            self.next[p][w] = v
            p = self.link[p]
        if p >= 0:
            q = self.next[p][w]
            self.link[v] = q if self.length[q] == self.length[p] + 1 else clone(p, q)
        return v

    def statistics(self, words: list[bytes]):
        """(state, matched length) after each word: the longest stretch that ends there and occurs in some template."""
        nxt, link, length = self.next, self.link, self.length
        state = n = 0
        for w in words:
            to = nxt[state].get(w)
            while to is None and state:
                state = link[state]
                n = length[state]
                to = nxt[state].get(w)
            if to is not None:
                state, n = to, n + 1
            yield state, n

    def stream(self, words: list[bytes], least: int):
        """(phrase hits as (first word, phrase), for each template its maximal matches of at least `least` words as (first, last, state))."""
        length, phrases, deepest = self.length, self.phrases, self.deepest
        hits: list[tuple[int, int]] = []
        matches: dict[int, list[tuple[int, int, int]]] = {}
        running: dict[int, tuple[int, int]] = {}  # template -> (first word, state) of the match that ends at the word before
        for i, (state, n) in enumerate(self.statistics(words)):
            if phrases[state]:
                hits.extend((i - size + 1, k) for k, size in phrases[state] if size <= n)
            if n < least and not running:
                continue
            now = {}
            for t, v in deepest[state].items() if n >= least else ():
                m = n if v == state else length[v]
                if m >= least:
                    now[t] = (i - m + 1, v)
            for t, (first, v) in running.items():
                if t not in now or now[t][0] != first:  # it does not go on
                    matches.setdefault(t, []).append((first, i - 1, v))
            running = now
        for t, (first, v) in running.items():
            matches.setdefault(t, []).append((first, len(words) - 1, v))
        return hits, matches


def chain(matches: dict[int, list[tuple[int, int, int]]], ends: list[dict[int, list[int]]], gap: int) -> dict[int, list[tuple[int, int, int]]]:
    """Per template: spans (first, last, template words covered) of matches that follow each other in text and template, each put
    at the first place of the template that still follows."""
    from bisect import bisect_right

    spans: dict[int, list[list[int]]] = {}
    for t, found in matches.items():
        own = spans.setdefault(t, [])
        for first, last, state in found:
            places = ends[state][t]
            if own and first - own[-1][1] - 1 <= gap and (k := bisect_right(places, own[-1][3])) < len(places):
                fresh = min(last - max(first, own[-1][1] + 1) + 1, places[k] - own[-1][3])
                own[-1][1:] = [last, own[-1][2] + fresh, places[k]]
            else:
                own.append([first, last, last - first + 1, places[0]])
    return {t: [tuple(s[:3]) for s in own] for t, own in spans.items()}


SCHEMA = "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<label:string,first:long,last:long,covered:double>>"


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: dict | None = None, base: dict | None = None, named: dict | None = None, least: int = 4, gap: int = 4, cover: float = 0.6) -> DataFrame:
    """One row per row of docs: counts of base phrases, labels, and the covered spans.

    least: shortest match that is chained; gap: words between chained matches; cover: share of a template's
    words that must be covered for its label. score is the largest such share of any template (1 at a phrase). named: further phrases that
    give a label without being base.
    """
    base = BASE if base is None else base
    labels, texts = [], []
    for label, all_of_it in (TEMPLATES if templates is None else templates).items():
        for t in all_of_it:
            labels.append(label)
            texts.append(words_of(t))
    named = NAMES if named is None else named
    phrases = [words_of(p) for p in (*base, *named)]
    of_phrase, n_base = [*base.values(), *named.values()], len(base)
    parts = texts + phrases
    out_schema = f"`{id_col}` {dict(docs.dtypes)[id_col]}, {SCHEMA}"

    def run(it):
        import pyarrow as pa

        auto = Automaton(parts, phrases)
        span = pa.list_(pa.struct([("label", pa.string()), ("first", pa.int64()), ("last", pa.int64()), ("covered", pa.float64())]))
        kind = pa.schema([*((n, pa.int64()) for n in ("n_words", "n_base", "first_word", "last_word")), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("spans", span)])
        for batch in it:
            rows = []
            for text in batch.column(1).to_pylist():
                words = words_of(text)
                hits, matches = auto.stream(words, least)
                found, spans, score = {of_phrase[k] for _, k in hits}, [], 1.0 if hits else 0.0
                hit_base = [(at, k) for at, k in hits if k < n_base]
                base_labels = ",".join(sorted({of_phrase[k] for _, k in hit_base}))
                for t, own in chain(matches, auto.ends, gap).items():
                    if t < len(texts):
                        for first, last, covered in own:
                            share = min(1.0, covered / len(texts[t]))
                            score = max(score, share)
                            if share >= cover:
                                found.add(labels[t])
                                spans.append({"label": labels[t], "first": first, "last": last, "covered": share})
                starts = [at for at, _ in hit_base]
                spans.sort(key=lambda x: (x["first"], x["last"], x["label"]))
                rows.append((len(words), len(hit_base), min(starts, default=None), max(starts, default=None), base_labels, ",".join(sorted(found)), score, spans))
            cols = list(zip(*rows, strict=True)) if rows else [[] for _ in kind]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(list(c), type=f.type) for c, f in zip(cols, kind, strict=True))], names=[id_col, *(f.name for f in kind)])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, out_schema)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return scan(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", F.size("spans").cast("long").alias("n_spans"))

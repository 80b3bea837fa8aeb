"""License scans by a positional index of license notices.

The words of all notices are counted over the documents once. A file that holds the key phrases of a notice is looked up by those of its words
of that notice that are rarest there; postings that agree on where the notice begins, give or take a few words, make a candidate;
a candidate whose key phrases stand in it is aligned with the file word by word.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import IS_WORD, LOWER, mix, prefix_hash, runs, slices, small_batches, span_hash, table

#: The phrases that count as base places, and their labels.
BASE_PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

#: Whole texts of short licenses, as words.
MIT = (
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software "
    "without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit "
    "persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all "
    "copies or substantial portions of the software the software is provided as is without warranty of any kind express or implied including but not limited to the "
    "warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages "
    "or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software"
)
ISC = (
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this "
    "permission notice appear in all copies the software is provided as is and the author disclaims all warranties with regard to this software including all implied "
    "warranties of merchantability and fitness in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever "
    "resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or "
    "performance of this software"
)
ZLIB = (
    "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this "
    "software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to "
    "the following restrictions 1 the origin of this software must not be misrepresented you must not claim that you wrote the original software if you use this software in "
    "a product an acknowledgment in the product documentation would be appreciated but is not required 2 altered source versions must be plainly marked as such and must "
    "not be misrepresented as being the original software 3 this notice may not be removed or altered from any source distribution"
)
BSD = (
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met 1 redistributions of source "
    "code must retain the above copyright notice this list of conditions and the following disclaimer 2 redistributions in binary form must reproduce the above copyright "
    "notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution this software is provided by the "
    "copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a "
    "particular purpose are disclaimed in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential "
    "damages including but not limited to procurement of substitute goods or services loss of use data or profits or business interruption however caused and on any theory of "
    "liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the "
    "possibility of such damage"
)

#: Notices as they are publicly known: (label, words of the notice, key phrases that must stand at their places).
NOTICES = [
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", ["gnu general public license", "version 3"]),
    ("gpl-2.0", "this work is licensed under the gnu general public license version 2", ["gnu general public license", "version 2"]),
    ("gpl-notice", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", ["gnu general public license", "free software foundation"]),
    ("lgpl", "it under the terms of the gnu lesser general public license as published by the free software foundation", ["gnu lesser general public license"]),
    ("agpl", "it under the terms of the gnu affero general public license as published by the free software foundation", ["gnu affero general public license"]),
    ("apache-2.0", "licensed under the apache license version 2 0", ["apache license", "version 2 0"]),
    ("apache-2.0", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0", ["in compliance with the license", "apache org licenses license 2 0"]),
    ("mit-grant", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["hereby granted free of charge", "any person obtaining a copy"]),
    ("mit-notice", "released under the mit license", ["mit license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ["source and binary forms", "with or without modification"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["with or without fee is hereby granted"]),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["unencumbered software", "public domain"]),
    ("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights", ["waived all copyright"]),
    ("cc-by-4.0", "this work is licensed under a creative commons attribution 4 0 international license", ["creative commons attribution", "4 0"]),
    ("cc-by-4.0", "licensed under cc by 4 0", ["cc by 4 0"]),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", ["cc by sa 4 0"]),
    ("cc-by-nc-4.0", "this work is licensed under a creative commons attribution noncommercial 4 0 international license", ["creative commons attribution noncommercial", "4 0"]),
    ("cc-by-sa-4.0", "this work is licensed under a creative commons attribution sharealike 4 0 international license", ["creative commons attribution sharealike", "4 0"]),
    ("boost", "distributed under the boost software license version 1 0", ["boost software license"]),
    ("zlib", ZLIB, ["in no event will the authors be held liable", "must not be misrepresented"]),
    ("isc-full", ISC, ["use copy modify and or distribute this software", "the author disclaims all warranties"]),
    ("mit-full", MIT, ["hereby granted free of charge", "the software is provided as is"]),
    ("bsd-2-clause-full", BSD, ["source and binary forms", "redistributions in binary form must reproduce", "this software is provided by the copyright holders and contributors as is"]),
]


#: Notices of so many words are whole texts.
WHOLE_TEXT = 50


def word_hashes(words: list[str]) -> np.ndarray:
    data = np.frombuffer(" ".join(words).encode(), np.uint8)
    ends = np.cumsum([len(w.encode()) + 1 for w in words]) - 1
    starts = ends - [len(w.encode()) for w in words]
    return mix(span_hash(prefix_hash(data), starts, ends))


class NoticeIndex:
    """The words of the notices by number, where they stand in each, and each word's rarity in the documents.

    ``df`` gives the documents that hold a word (by hash) and ``n`` their number; without them all words are alike.
    """

    def __init__(self, notices: list[tuple[str, str, list[str]]] = NOTICES, df: dict[int, int] | None = None, n: int = 0, rare: int = 24, cover: float = 0.7, slack: int = 4) -> None:
        self.rare, self.cover, self.slack = rare, cover, slack
        self.labels = [x[0] for x in notices]
        hashes = [word_hashes(x[1].split()) for x in notices]
        self.words = np.unique(np.concatenate([*hashes, *(word_hashes(p.split()) for x in notices for p in x[2])]))
        self.numbered = [np.searchsorted(self.words, h) for h in hashes]
        self.must = [[tuple(np.searchsorted(self.words, word_hashes(p.split())).tolist()) for p in x[2]] for x in notices]
        self.offsets = [[next((i for i in range(len(own)) if tuple(own[i : i + len(p)].tolist()) == p), 0) for p in must] for own, must in zip(self.numbered, self.must, strict=True)]
        self.whole = [len(own) >= WHOLE_TEXT for own in self.numbered]
        seen = np.array([(df or {}).get(int(w), 0) for w in self.words.view(np.int64)])
        self.rarity = np.log((n + 2) / (seen + 1)) if n else np.ones(len(self.words))
        self.weights = [self.rarity[own] for own in self.numbered]

    def numbers(self, word: np.ndarray) -> np.ndarray:
        """Each word's number among the words of the notices, -1 if none has it."""
        at = np.minimum(np.searchsorted(self.words, word), len(self.words) - 1)
        return np.where(self.words[at] == word, at, -1)

    def phrase_places(self, number: np.ndarray, text: np.ndarray) -> dict[tuple[int, ...], np.ndarray]:
        """Where each key phrase stands within a text."""
        places: dict[tuple[int, ...], np.ndarray] = {}
        for phrase in {p for must in self.must for p in must}:
            at = np.flatnonzero(number[: max(0, len(number) - len(phrase) + 1)] == phrase[0])
            for k in range(1, len(phrase)):
                at = at[number[at + k] == phrase[k]]
            places[phrase] = at[text[at] == text[at + len(phrase) - 1]] if len(at) else at
        return places

    def looked_up(self, number: np.ndarray, notice: int) -> np.ndarray:
        """Where the notice would begin by each place in a text of the ``rare`` rarest of its words that the notice has, and of the key phrases' words; sorted."""
        own = np.unique(number)
        own = own[np.isin(own, self.numbered[notice])]
        chosen = own[np.lexsort((own, -self.rarity[own]))[: self.rare]]
        chosen = np.union1d(chosen, [w for phrase in self.must[notice] for w in phrase])
        # postings: places of the notice by word
        order = np.argsort(self.numbered[notice], kind="stable")
        key = self.numbered[notice][order]
        spot = np.flatnonzero(np.isin(number, chosen))
        lo, hi = np.searchsorted(key, number[spot]), np.searchsorted(key, number[spot], side="right")
        n = hi - lo
        posting = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        return np.sort(np.repeat(spot, n) - order[posting])

    def aligned(self, given: np.ndarray, notice: int) -> np.ndarray:
        """Which words of the notice a longest common subsequence with the word numbers ``given`` holds."""
        own = self.numbered[notice].tolist()
        table = np.zeros((len(own) + 1, len(given) + 1), np.int32)
        for i, x in enumerate(own):
            step = np.maximum(table[i, 1:], np.where(given == x, table[i, :-1] + 1, 0))
            table[i + 1, 1:] = np.maximum.accumulate(step)
        held, i, j = np.zeros(len(own), bool), len(own), len(given)
        while i and j:
            if table[i, j] == table[i - 1, j]:
                i -= 1
            elif table[i, j] == table[i, j - 1]:
                j -= 1
            else:
                i, j = i - 1, j - 1
                held[i] = True
        return held

    def matches(self, word: np.ndarray, text: np.ndarray, first: np.ndarray) -> list[tuple[int, int, float]]:
        """(text, notice, coverage) of notices that stand in a text, perhaps with edits, or cut off at its ends.

        ``first`` has each text's first word and, at its end, the number of words. A notice is looked up only in texts that hold
        all of its key phrases (one of them, if it is the whole text of a license), and aligned only where they stand; this holds for every match, so none is lost.
        """
        number = self.numbers(word)
        places = self.phrase_places(number, text)
        found: dict[tuple[int, int], float] = {}
        for k, must in enumerate(self.must):
            owners = [np.unique(text[places[phrase]]) for phrase in must]
            holders = reduce(np.union1d if self.whole[k] else np.intersect1d, owners)
            for t in holders.tolist():
                low, high = int(first[t]), int(first[t + 1])
                at = [p[np.searchsorted(p, low) : np.searchsorted(p, high)] - low for p in (places[phrase] for phrase in must)]
                share = self.coverage(number[low:high], k, at)
                if share >= self.cover:
                    found[t, k] = share
        return [(t, k, share) for (t, k), share in found.items()]

    def coverage(self, number: np.ndarray, notice: int, at: list[np.ndarray]) -> float:
        """The best coverage of a notice in one text, 0 if no candidate has its key phrases; ``at`` has the places of each of them.

        In whole texts of licenses, other key phrases than one may be edited as well, but hold six tenths of their words.
        """
        size, must, weights = len(self.numbered[notice]), self.must[notice], self.weights[notice]
        start = self.looked_up(number, notice)
        if not len(start):
            return 0.0
        # postings whose beginnings are near each other are one candidate
        new = np.append(True, start[1:] > start[:-1] + self.slack)
        lo, hi = start[new], start[np.append(np.flatnonzero(new)[1:], len(start)) - 1]
        # words may be inserted by up to ``slack`` a word of the notice, so it reaches no farther than this from a key phrase
        reach, best, seen = self.slack * size, 0.0, set()
        whole, offsets = self.whole[notice], self.offsets[notice]
        for place, offset in list(zip(at, offsets, strict=True))[: None if whole else 1]:
            for p in (place - offset).tolist():
                for g in range(int(np.searchsorted(hi, p - reach)), int(np.searchsorted(lo, p + reach, side="right"))):
                    begin = max(0, int(lo[g]) - self.slack, p - reach)
                    end = min(len(number), int(hi[g]) + size + self.slack, p + reach + size)
                    stand = [np.searchsorted(x, begin) < np.searchsorted(x, end - len(m), side="right") for x, m in zip(at, must, strict=True)]
                    if (begin, end) in seen or not (any(stand) if whole else all(stand)):
                        continue
                    seen.add((begin, end))
                    held = self.aligned(number[begin:end], notice)
                    if all(ok or held[o : o + len(m)].mean() >= 0.6 for ok, o, m in zip(stand, offsets, must, strict=True)):
                        best = max(best, float(weights[held].sum() / max(weights.sum(), 1e-9)))
                    if best > 1 - 1e-9:
                        return best
        return best


def word_counts(docs: DataFrame, notices: list[tuple[str, str, list[str]]], text_col: str = "text") -> tuple[dict[int, int], int]:
    """How many of all texts hold each word of the notices, and the number of texts; a task sends a row for each of these words."""
    known = np.unique(np.concatenate([word_hashes(x[1].split()) for x in notices]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(len(known), np.int64), 0
        for batch in batches:
            for _, data, offsets in slices(batch.column(0), 1_000_000):
                starts, ends, text = runs(IS_WORD[data], offsets)
                n += len(offsets) - 1
                if len(starts):
                    word = mix(span_hash(prefix_hash(LOWER[data]), starts, ends))
                    at = np.minimum(np.searchsorted(known, word), len(known) - 1)
                    own = np.flatnonzero(known[at] == word)
                    total += np.bincount(np.unique(text[own] * len(known) + at[own]) % len(known), minlength=len(known))
        rows = np.append(known.view(np.int64), 0), np.append(total, n), np.append(np.zeros(len(known), bool), True)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in rows], names=["word", "n", "all"])

    counted = small_batches(docs).select(F.col(text_col).alias("text")).mapInArrow(run, "word long, n long, all boolean").groupBy("word", "all").agg(F.sum("n").alias("n")).collect()
    return {r.word: r.n for r in counted if not r["all"]}, sum(r.n for r in counted if r["all"])


def scan(docs: DataFrame, notices: list[tuple[str, str, list[str]]] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: words, places of base phrases, base labels, all labels, and a score from 0 to 1.

    Notices are told by words that are rare in ``docs`` themselves, counted over all of them first. The score is the best coverage of a verified notice, one half at least if a base phrase
    stands somewhere, else 0. Whole texts are read; null counts as empty; without base
    places the first and last word are null and the labels are empty strings. Repeated rows come
    back as often as they came, an empty table gives no rows, other columns are not read.
    """
    notices = notices or NOTICES
    df, total = word_counts(docs, notices, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = NoticeIndex(notices, df, total)
        phrases = [(word_hashes(p.split()), label) for p, label in BASE_PHRASES.items()]
        for batch in batches:
            columns: list[list] = [[] for _ in range(7)]
            for _, data, offsets in slices(batch.column(1), 1_000_000):
                n = len(offsets) - 1
                low = LOWER[data]
                starts, ends, text = runs(IS_WORD[data], offsets)
                word = mix(span_hash(prefix_hash(low), starts, ends)) if len(starts) else np.zeros(0, np.uint64)
                first = np.searchsorted(text, np.arange(n + 1))
                count, labels, base = np.zeros(n, np.int64), [set() for _ in range(n)], [set() for _ in range(n)]
                low_at, high_at = np.full(n, np.iinfo(np.int64).max), np.full(n, -1)
                for hashes, label in phrases:
                    at = np.flatnonzero(word[: max(0, len(word) - len(hashes) + 1)] == hashes[0])
                    for k in range(1, len(hashes)):
                        at = at[word[at + k] == hashes[k]]
                    at = at[at + len(hashes) <= first[text[at] + 1]]
                    own = text[at]
                    np.add.at(count, own, 1)
                    np.minimum.at(low_at, own, at - first[own])
                    np.maximum.at(high_at, own, at - first[own])
                    for t in set(own.tolist()):
                        base[t].add(label)
                score = np.where(count > 0, 0.5, 0.0)
                for t, k, share in index.matches(word, text, first):
                    labels[t].add(index.labels[k])
                    score[t] = max(score[t], min(1.0, share))
                columns[0] += np.diff(first).tolist()
                columns[1] += count.tolist()
                columns[2] += [int(x) if c else None for x, c in zip(low_at, count, strict=True)]
                columns[3] += [int(x) if c else None for x, c in zip(high_at, count, strict=True)]
                columns[4] += [",".join(sorted(b)) for b in base]
                columns[5] += [",".join(sorted(b | x)) for b, x in zip(base, labels, strict=True)]
                columns[6] += score.tolist()
            kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64()]
            arrays = [batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"])

    chosen = small_batches(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return chosen.mapInArrow(run, "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))

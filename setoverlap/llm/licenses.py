"""License scans by a positional rare-token index.

Passages of public licences (`license_texts`) are templates. Words get an inverse document frequency over the templates;
each template's rarest words are posted as word -> (template, position). A file's rare words vote for
(template, file position - template position); votes on one line of that plane, or within DRIFT of it, make a candidate.
Its words are compared in order, the line giving way by up to DRIFT places where a word was put in or left out;
passages with enough words in place and all their mandatory key phrases count.

Defined cases: null text reads as empty (no words, null places, score 0); repeated rows each get a row; an empty
table gives an empty result; other columns are not read. Words are found on UTF-8 bytes, where all bytes above
127 belong to words, as the contract's class has it.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict

from pyspark.sql import DataFrame

from setoverlap.llm.common import id_and_text, map_rows
from setoverlap.llm.license_texts import PASSAGES

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
# Base phrases with their labels.
BASE = [("mit", b"mit license"), ("apache", b"apache license"), ("gpl", b"general public license")]
RARE_WORDS = 6
LEAST_VOTES = 2
LEAST_SHARE = 0.6
DRIFT = 2


def words_of(text: str) -> list[bytes]:
    return WORD.findall(text.encode("utf-8", "surrogatepass").lower())


def aligned(words: list[bytes], want: list[bytes], start: int) -> tuple[int, int]:
    """How many of a passage's words stand in order from about `start`, and where the last of them stands."""
    at, hits, last = start, 0, start
    for w in want:
        for d in (0, 1, -1, 2, -2)[: 1 + 2 * DRIFT]:
            if 0 <= at + d < len(words) and at + d >= last and words[at + d] == w:
                at, hits, last = at + d, hits + 1, at + d + 1
                break
        at += 1
    return hits, last


class RareIndex:
    def __init__(self, templates=PASSAGES):
        self.labels = [t[0] for t in templates]
        self.words = [words_of(t[1]) for t in templates]
        self.keys = [[words_of(k) for k in t[2]] for t in templates]
        df = Counter(w for ws in self.words for w in set(ws))
        idf = {w: math.log((1 + len(templates)) / n) for w, n in df.items()}
        self.postings: dict[bytes, list[tuple[int, int]]] = defaultdict(list)
        for t, ws in enumerate(self.words):
            rare = set(sorted(set(ws), key=lambda w: (-idf[w], w))[:RARE_WORDS])
            for p, w in enumerate(ws):
                if w in rare:
                    self.postings[w].append((t, p))

    def judge(self, words: list[bytes], t: int, start: int) -> float | None:
        """Share of the passage's words in place, or None where it is too small or a key phrase is missing."""
        want = self.words[t]
        hits, end = aligned(words, want, start)
        if hits < LEAST_SHARE * len(want):
            return None
        near = words[max(0, start - DRIFT) : max(end, start + len(want)) + DRIFT]
        has = all(any(near[k : k + len(key)] == key for k in range(len(near) - len(key) + 1)) for key in self.keys[t])
        return hits / len(want) if has else None

    def find(self, words: list[bytes]) -> list[tuple[float, str, int]]:
        """(share of the passage's words in place, label, start) of each verified passage."""
        votes: Counter = Counter()
        for i, w in enumerate(words):
            if w in self.postings:
                for t, p in self.postings[w]:
                    votes[t, i - p] += 1
        out = []
        for (t, start), n in votes.items():
            near = n + sum(votes.get((t, start + d), 0) for d in range(-DRIFT, DRIFT + 1) if d)
            if near >= min(LEAST_VOTES, len(self.words[t])) and (share := self.judge(words, t, start)) is not None:
                out.append((share, self.labels[t], start))
        return out


def base_places(words: list[bytes]) -> tuple[list[int], set[str]]:
    """Starts of base phrases, and their labels; the last word of each phrase is looked up first."""
    places, labels = [], set()
    for i, w in enumerate(words):
        if w == b"license":
            for label, phrase in BASE:
                p = phrase.split()
                s = i - len(p) + 1
                if s >= 0 and words[s : i + 1] == p:
                    places.append(s)
                    labels.add(label)
    return places, labels


def licenses(df: DataFrame, templates=PASSAGES) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""

    def setup():
        index = RareIndex(templates)

        def row(i, text):
            words = words_of(text)
            places, base = base_places(words) if b"license" in words else ([], set())
            found = index.find(words)
            score = max([s for s, _, _ in found], default=0.0)
            return (i, len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)),
                    ",".join(sorted(base | {x for _, x, _ in found})), max(score, 1.0 if base else 0.0))

        return row

    return map_rows(id_and_text(df), setup, "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double")

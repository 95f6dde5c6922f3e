"""License scans with a generalised suffix automaton over license words.

The automaton holds all templates and phrases. A text is streamed through it: at
each word the state and length tell the longest run of words, ending here, that
some template has (matching statistics). Runs that can't be extended and are long
enough are chained, across small gaps, for each template that holds them; of the spans
that result the ones that cover most words stay, and none of them overlap.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import LOWER, row_texts
from .license_texts import PHRASES, TEMPLATES

#: Least words of a run, most words between chained runs; a span counts from this share of its template's words, or this many.
MIN_RUN, MAX_GAP, SHARE, ENOUGH = 3, 4, 0.6, 8

#: Bytes that aren't part of a word to spaces, A-Z to lower case.
_WORDS = bytes(b if b >= 0x80 or chr(b).isalnum() else 32 for b in LOWER)


def license_words(text: bytes) -> list[bytes]:
    """Words: runs of lower-cased letters, digits and bytes above ASCII."""
    return text.translate(_WORDS).split()


class SuffixAutomaton:
    """A generalised suffix automaton; each state knows the sequences that hold its words."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length, self.owners = [-1], [0], [set()]
        self.ends: dict[int, list[tuple[int, int]]] = {}

    def _state(self, length: int, link: int, moves: dict[int, int]) -> int:
        self.next.append(moves)
        self.link.append(link)
        self.length.append(length)
        self.owners.append(set())
        return len(self.next) - 1

    def _split(self, p: int, q: int, word: int) -> int:
        """The part of q whose words p followed by ``word`` reaches."""
        if self.length[q] == self.length[p] + 1:
            return q
        twin = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]))
        self.owners[twin] |= self.owners[q]
        self.link[q] = twin
        while p >= 0 and self.next[p].get(word) == q:
            self.next[p][word] = twin
            p = self.link[p]
        return twin

    def add(self, sequence: list[int], owner: int) -> int:
        """Adds a sequence, starting at the root; returns its state."""
        at = 0
        for word in sequence:
            if word in self.next[at]:
                at = self._split(at, self.next[at][word], word)
            else:
                p, new = at, self._state(self.length[at] + 1, 0, {})
                while p >= 0 and word not in self.next[p]:
                    self.next[p][word] = new
                    p = self.link[p]
                if p >= 0:
                    self.link[new] = self._split(p, self.next[p][word], word)
                at = new
            s = at
            while s > 0:
                self.owners[s].add(owner)
                s = self.link[s]
        return at

    def advance(self, state: int, length: int, word: int) -> tuple[int, int]:
        """Matching statistics after one more word."""
        while state and word not in self.next[state]:
            state = self.link[state]
            length = self.length[state]
        if word in self.next[state]:
            return self.next[state][word], length + 1
        return 0, 0


class LicenseScanner:
    def __init__(self, templates=None, phrases=None):
        templates, phrases = templates or TEMPLATES, phrases or PHRASES
        self.vocabulary: dict[bytes, int] = {}
        self.automaton, self.labels, self.sizes = SuffixAutomaton(), [], []
        code = lambda text: [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in license_words(text.encode())]
        ends = []
        for label, text in [*templates, *((v, k) for k, v in phrases.items())]:
            sequence = code(text)
            self.labels.append(label)
            self.sizes.append(len(sequence))
            state = self.automaton.add(sequence, len(self.labels) - 1)
            if len(self.labels) > len(templates):
                ends.append((sequence, label))
        # After all are in: the states at which a phrase ends (its own state and those below it in the link tree).
        self.phrase_at: dict[int, list[tuple[int, str]]] = {}
        for sequence, label in ends:
            state = 0
            for word in sequence:
                state = self.automaton.next[state][word]
            for s in range(1, len(self.automaton.next)):
                above = s
                while above > 0 and above != state:
                    above = self.automaton.link[above]
                if above == state:
                    self.phrase_at.setdefault(s, []).append((len(sequence), label))
        self.owners = [sorted(o for o in owners if o < len(templates)) for owners in self.automaton.owners]

    def runs(self, ids: list[int | None]) -> Iterator[tuple[int, int, int, list[tuple[int, str]]]]:
        """(end, length, state, phrases that end here) wherever the automaton holds the last words."""
        state = length = 0
        step, phrase_at = self.automaton.advance, self.phrase_at
        for i, word in enumerate(ids):
            if word is None:
                if length:
                    state = length = 0
                continue
            state, length = step(state, length, word)
            ended = phrase_at.get(state, ())
            if length > 1 or ended:
                yield i + 1, length, state, ended

    def scan(self, text: bytes) -> tuple:
        """n_words, base starts, base labels, spans (label, first word, past the last, matched words)."""
        tokens = license_words(text)
        ids = list(map(self.vocabulary.get, tokens))
        starts, base, matches = [], set(), []
        last = None
        for end, length, state, ended in self.runs(ids):
            for size, label in ended:
                if length >= size:
                    starts.append(end - size)
                    base.add(label)
            if last and not (end == last[0] + 1 and length == last[1] + 1):
                matches.append(last)
            last = (end, length, state)
        if last:
            matches.append(last)
        return len(tokens), starts, base, self.chain(matches)

    def chain(self, matches: list[tuple[int, int, int]]) -> list[tuple[str, int, int, int]]:
        """Maximal runs of MIN_RUN words or more, at most MAX_GAP words apart, as covered spans of their templates; the best of overlapping ones."""
        open_spans: dict[int, list[int]] = {}
        done = []
        for end, length, state in matches:
            start = end - length
            for owner in self.owners[state] if length >= MIN_RUN else ():
                span = open_spans.get(owner)
                if span and start <= span[1] + MAX_GAP:
                    open_spans[owner] = [min(span[0], start), max(span[1], end), span[2] + max(0, end - max(start, span[1]))]
                else:
                    if span:
                        done.append((owner, *span))
                    open_spans[owner] = [start, end, length]
        done += [(owner, *span) for owner, span in open_spans.items()]
        best = sorted((-n, self.labels[o], a, b) for o, a, b, n in done if n >= min(ENOUGH, SHARE * self.sizes[o]))
        out: list[tuple[str, int, int, int]] = []
        for n, label, a, b in best:
            if all(b <= x or y <= a for _, x, y, _ in out):
                out.append((label, a, b, -n))
        return sorted(out, key=lambda s: (s[1], s))


def _scan(scanner: LicenseScanner):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            for text in row_texts(batch.column("text")):
                n, starts, base, spans = scanner.scan(text)
                row = (n, len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(base | {s[0] for s in spans})), sum(b - a for _, a, b, _ in spans) / n if n else 0.0, ",".join(f"{label}:{a}:{b}" for label, a, b, _ in spans))
                for column, value in zip(out, row):
                    column.append(value)
            kinds = ["int64"] * 4 + ["string", "string", "float64", "string"]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(out, kinds))], names=["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"])

    return run


def scan_licenses(docs: DataFrame, scanner: LicenseScanner | None = None) -> DataFrame:
    """Per row: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans.

    n_base counts all places of the phrases (words from 0); labels adds those of
    covered template spans; score is the share of words in spans; spans lists
    label:first:past-the-last.

    Defined cases: null or empty text has no words, null first_word and last_word,
    empty strings and score 0. doc_id may be null or repeat: rows stand alone. An empty table gives no rows.
    """
    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans string"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_scan(scanner or LicenseScanner()), schema)

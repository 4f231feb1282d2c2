"""Deterministic automaton of all correct byte-pair tokenizations, built merge by merge.

Arcs are labelled with tokens. The automaton starts with one state that loops on every base symbol and so
accepts every segmentation. Each merge ``u v -> uv`` then adds a gadget: the arcs labelled ``u`` get a target
of their own, that target loses its arc ``v`` (the pair may no longer stand unmerged), and every state that
still has an arc ``u`` gets an arc ``uv`` to where ``v`` led. All arcs of one label share their target, so a
state is known by the last token read, and an input has exactly one accepted segmentation.

A full arc table would have states x tokens entries. It is kept by differences: a state holds the state it was
copied from, the merge that made it, and the arcs it lost; an arc ``x`` was given to a state exactly if the state
still had the arc of x's left part when x was made. Looked-up transitions go into a table.
"""

from __future__ import annotations

import functools
import json

import ahocorasick

#: Stands for the end-of-word suffix inside labels; a private code point that byte-level symbols never use.
WORD_END = "\ue000"
NEVER = 1 << 60


def byte_symbols() -> dict[str, int]:
    """Byte of each symbol of the byte-level alphabet: visible bytes stand for themselves, the others follow from 256 on."""
    visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in visible]
    return {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(hidden)}


class MergeAutomaton:
    """Encoder of pre-split words by table-driven transitions.

    ``labels[i]`` is the text of token i in byte-level symbols, ``merges`` the pairs of token ids in order of priority
    with their result. Words are bytes, held as text with a character for each byte (latin-1). An empty word has no
    tokens. A word with a byte outside the base alphabet raises ``ValueError``.
    """

    def __init__(self, labels: list[str], base: list[int], merges: list[tuple[int, int, int]], suffix: str = "", table_limit: int = 2_000_000):
        self.labels = labels
        self.suffix = suffix
        self.parent, self.made, self.lost = [-1], [-1], [{}]
        self.target = [-1] * len(labels)
        self.left: dict[int, tuple[int, int]] = {}
        members = [len(base) + 1]  # the start state keeps state 0 in use
        for token in base:
            self.target[token] = 0
        for when, (u, v, uv) in enumerate(merges):
            behind_u, behind_v = self.target[u], self.target[v]
            if members[behind_u] > 1 or u == v:  # for u == v the arc uv leads to the state as it was
                members[behind_u] -= 1
                self.target[u] = len(self.parent)
                self.parent.append(behind_u)
                self.made.append(when)
                self.lost.append({v: when})
                members.append(1)
            else:
                self.lost[behind_u].setdefault(v, when)
            self.target[uv] = behind_v
            members[behind_v] += 1
            self.left[uv] = (u, when)
        self.rows: dict[int, dict[int, int]] = {}
        self.known, self.table_limit = 0, table_limit
        self.length = [0] * len(labels)
        self.words = ahocorasick.Automaton()
        symbols = byte_symbols()
        for token in [*base, *(uv for _, _, uv in merges)]:
            ends = bool(suffix) and labels[token].endswith(suffix)
            word = "".join(chr(symbols[c]) for c in (labels[token].removesuffix(suffix) if ends else labels[token])) + WORD_END * ends
            self.length[token] = len(word)
            self.words.add_word(word, (token, len(word)))
        self.words.make_automaton()

    @property
    def n_states(self) -> int:
        return len(self.parent)

    def has_arc(self, state: int, token: int) -> bool:
        """Whether the finished automaton has an arc ``token`` out of ``state``."""
        label, until = token, NEVER
        while True:
            node, limit = state, NEVER
            while node >= 0:
                gone = self.lost[node].get(label, NEVER)
                if gone <= until and gone < limit:
                    return False
                limit = min(limit, self.made[node])
                node = self.parent[node]
            if label not in self.left:
                return True
            label, until = self.left[label]

    def step(self, state: int, token: int) -> int:
        """The state behind the arc, or -1 if there is none; kept in the transition table."""
        if self.known >= self.table_limit:
            self.rows.clear()
            self.known = 0
        self.known += 1
        after = self.target[token] if self.has_arc(state, token) else -1
        self.rows.setdefault(state, {})[token] = after
        return after

    def encode(self, word: str) -> list[int]:
        """Token ids of one pre-split word: the only accepted segmentation, found left to right in one pass."""
        if not word:
            return []
        if self.suffix:
            word += WORD_END
        n = len(word)
        state, last = [-1] * (n + 1), [0] * (n + 1)
        state[0] = 0
        rows, none = self.rows, {}
        for end, (token, length) in self.words.iter(word):
            end += 1
            if state[end] < 0 and (before := state[end - length]) >= 0:
                after = rows.get(before, none).get(token)
                if after is None:
                    after = self.step(before, token)
                if after >= 0:
                    state[end], last[end] = after, token
        if state[n] < 0:
            raise ValueError("a byte lies outside the base alphabet")
        out, length = [], self.length
        while n:
            token = last[n]
            out.append(token)
            n -= length[token]
        out.reverse()
        return out


def labels_of(definition: dict) -> list[str]:
    """Arc labels by token id; added tokens spell themselves."""
    named = [*definition["model"]["vocab"].items(), *((a["content"], a["id"]) for a in definition.get("added_tokens", []))]
    labels = [""] * (max((token for _, token in named), default=-1) + 1)
    for label, token in named:
        labels[token] = label
    return labels


def from_definition(definition: dict) -> MergeAutomaton:
    """Compile the model part of a tokenizer file in the public JSON format."""
    model = definition["model"]
    suffix = model.get("end_of_word_suffix") or ""
    vocab, labels = model["vocab"], labels_of(definition)
    pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
    merges = [(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs]
    made = {uv for _, _, uv in merges}
    base = [t for label, t in vocab.items() if t not in made and len(label.removesuffix(suffix) if suffix and label != suffix else label) == 1]
    return MergeAutomaton(labels, base, merges, suffix)


@functools.lru_cache(maxsize=4)
def load(path: str) -> MergeAutomaton:
    """The automaton of a tokenizer file; each process compiles it once."""
    with open(path, encoding="utf-8") as source:
        return from_definition(json.load(source))


@functools.lru_cache(maxsize=4)
def arc_labels(path: str) -> list[str]:
    """Arc labels of a tokenizer file: all that decoding needs."""
    with open(path, encoding="utf-8") as source:
        return labels_of(json.load(source))

"""Weighted transducers: the three machines as arc tables, composition, search, and n-best reranking."""

from __future__ import annotations

import heapq
import math
import pickle
from collections import defaultdict
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from itertools import chain
from typing import BinaryIO

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast, SparkContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.sources.tables import dropped, written

EPS = ""


@dataclass
class Fst:
    """A small machine on the driver or in a task: arcs by state (in, out, weight, target), final weights."""

    start: int = 0
    arcs: dict[int, list[tuple[str, str, float, int]]] = field(default_factory=lambda: defaultdict(list))
    finals: dict[int, float] = field(default_factory=dict)

    def add(self, src: int, ilab: str, olab: str, w: float, dst: int) -> None:
        self.arcs[src].append((ilab, olab, w, dst))


def ctc_arcs(alphabet: str, blank: str = "_") -> list[tuple[int, int, str, str, float]]:
    """Clean-up machine: the state is the last symbol; a repeat and a blank emit nothing."""
    symbols = [c for c in alphabet if c != blank]
    at = {c: i + 1 for i, c in enumerate(symbols)} | {blank: 0}
    return [(at[a], at[b], b, EPS if b == blank or a == b else b, 0.0) for a in [blank, *symbols] for b in [blank, *symbols]]


def lexicon_arcs(lex: DataFrame) -> DataFrame:
    """src, dst, ilab, olab: a prefix tree of pronunciations by state name; at a leaf the word leads back to the root.

    States are named by their prefix, so building is a distinct over exploded prefixes: no driver, no loop.
    """
    steps = lex.select("phones", F.explode(F.expr("sequence(1, length(phones))")).alias("i"))
    tree = steps.select(F.expr("substring(phones, 1, i - 1)").alias("src"), F.expr("substring(phones, 1, i)").alias("dst"), F.expr("substring(phones, i, 1)").alias("ilab"), F.lit(EPS).alias("olab")).distinct()
    leaves = lex.where("length(phones) > 0").select(F.col("phones").alias("src"), F.lit("").alias("dst"), F.lit(EPS).alias("ilab"), F.col("word").alias("olab")).distinct()
    return tree.unionByName(leaves)


def lm_arcs(model: DataFrame, weights: DataFrame, order: int) -> DataFrame:
    """src (context), dst, olab, cost: a word arc for each n-gram, an empty one for each context's back-off."""
    from clipflow.operators.lm import suffix_of

    whole = F.trim(F.concat_ws(" ", "ctx", "w"))
    words = model.select(F.col("ctx").alias("src"), F.when(F.col("order") < order, whole).otherwise(suffix_of(whole)).alias("dst"), F.col("w").alias("olab"), (-F.log("p")).alias("cost"))
    back = weights.select(F.col("ctx").alias("src"), suffix_of(F.col("ctx")).alias("dst"), F.lit(EPS).alias("olab"), F.when(F.col("bow") > 0, -F.log("bow")).alias("cost"))
    return words.unionByName(back)


def compose(a: Fst, b: Fst) -> Fst:
    """a's outputs are b's inputs. A filter state keeps empty moves of the two in one order, so no path is counted twice."""
    out, number = Fst(), {}

    def state(s: tuple[int, int, int]) -> int:
        if s not in number:
            number[s] = len(number)
            todo.append(s)
        return number[s]

    todo: list[tuple[int, int, int]] = []
    out.start = state((a.start, b.start, 0))
    while todo:
        s = todo.pop()
        p, q, f = s
        me = number[s]
        if p in a.finals and q in b.finals:
            out.finals[me] = a.finals[p] + b.finals[q]
        for i, o, w, t in a.arcs.get(p, ()):
            if o == EPS:
                if f != 2:  # a moves alone: before b may
                    out.add(me, i, EPS, w, state((t, q, 1)))
                continue
            for bi, bo, bw, bt in b.arcs.get(q, ()):
                if bi == o:
                    out.add(me, i, bo, w + bw, state((t, bt, 0)))
        for bi, bo, bw, bt in b.arcs.get(q, ()):
            if bi == EPS:
                out.add(me, EPS, bo, bw, state((p, bt, 2)))
    return connect(out)


def connect(m: Fst) -> Fst:
    """Only states on a path from start to a final one."""
    ahead, todo = {m.start}, [m.start]
    while todo:
        for *_, t in m.arcs.get(todo.pop(), ()):
            if t not in ahead:
                ahead.add(t)
                todo.append(t)
    into = defaultdict(list)
    for s, arcs in m.arcs.items():
        for *_, t in arcs:
            into[t].append(s)
    back, todo = set(m.finals) & ahead, list(set(m.finals) & ahead)
    while todo:
        for s in into[todo.pop()]:
            if s in ahead and s not in back:
                back.add(s)
                todo.append(s)
    keep = Fst(m.start, finals={s: w for s, w in m.finals.items() if s in back})
    for s in back:
        keep.arcs[s] = [x for x in m.arcs.get(s, ()) if x[-1] in back]
    return keep


def determinise(m: Fst) -> Fst:
    """By subsets with residual weights, for acceptors without empty arcs; equal strings keep their least weight."""
    out, number = Fst(), {}

    def state(sub: tuple) -> int:
        if sub not in number:
            number[sub] = len(number)
            todo.append(sub)
        return number[sub]

    todo: list[tuple] = []
    out.start = state(((m.start, 0.0),))
    while todo:
        sub = todo.pop()
        me = number[sub]
        ends = [r + m.finals[s] for s, r in sub if s in m.finals]
        if ends:
            out.finals[me] = min(ends)
        by: dict[str, dict[int, float]] = defaultdict(dict)
        for s, r in sub:
            for i, _, w, t in m.arcs.get(s, ()):
                by[i][t] = min(by[i].get(t, math.inf), r + w)
        for label, targets in sorted(by.items()):
            least = min(targets.values())
            out.add(me, label, label, least, state(tuple(sorted((t, round(w - least, 12)) for t, w in targets.items()))))
    return out


def remove_epsilon(m: Fst) -> Fst:
    """An acceptor without empty arcs: each state takes over the arcs and final weights that empty paths lead to, at their cost."""
    out = Fst(m.start)
    for s in {m.start, *m.arcs, *m.finals, *(x[-1] for arcs in m.arcs.values() for x in arcs)}:
        cost, heap = {s: 0.0}, [(0.0, s)]
        while heap:
            c, q = heapq.heappop(heap)
            if c > cost[q]:
                continue
            for i, o, w, t in m.arcs.get(q, ()):
                if i == EPS and o == EPS and c + w < cost.get(t, math.inf):
                    cost[t] = c + w
                    heapq.heappush(heap, (c + w, t))
        for q, c in cost.items():
            if q in m.finals:
                out.finals[s] = min(out.finals.get(s, math.inf), c + m.finals[q])
            for i, o, w, t in m.arcs.get(q, ()):
                if i != EPS or o != EPS:
                    out.add(s, i, o, c + w, t)
    return connect(out)


def best_strings(m: Fst, n: int = 1, most: int = 100_000) -> list[tuple[tuple[str, ...], float]]:
    """The n cheapest paths' outputs, by cost; weights are not negative."""
    heap, found, seen, tick = [(0.0, 0, m.start, ())], [], set(), 0
    while heap and len(found) < n and tick < most:
        cost, _, s, out = heapq.heappop(heap)
        if s == -1:
            if out not in seen:
                seen.add(out)
                found.append((out, cost))
            continue
        if s in m.finals:
            tick += 1
            heapq.heappush(heap, (cost + m.finals[s], tick, -1, out))
        for _, o, w, t in m.arcs.get(s, ()):
            tick += 1
            heapq.heappush(heap, (cost + w, tick, t, out if o == EPS else (*out, o)))
    return found


def prefix_tree(lexicon: list[tuple[str, str]]) -> tuple[list[dict[str, int]], list[list[str]]]:
    """Nodes as (symbol -> node), and the words that end at each."""
    tree: list[dict[str, int]] = [{}]
    words: list[list[str]] = [[]]
    for word, phones in lexicon:
        node = 0
        for p in phones:
            if p not in tree[node]:
                tree[node][p] = len(tree)
                tree.append({})
                words.append([])
            node = tree[node][p]
        if phones:
            words[node].append(word)
    return tree, words


@dataclass
class Decoder:
    """Clean-up and lexicon tree searched frame by frame, the language model composed lazily at word ends.

    The phoneme model is not part of it: another lexicon or language model is a new Decoder over the same lattices.
    ``lexicon``: (word, phones) pairs; ``lm(history, word)`` -> log probability.
    """

    lexicon: list[tuple[str, str]]
    lm: dict[tuple[str, ...], float] = field(default_factory=dict)
    back: dict[tuple[str, ...], float] = field(default_factory=dict)
    order: int = 2
    beam: float = 12.0
    max_active: int = 300
    weight: float = 1.0
    floor: float = math.log(1e-7)

    def __post_init__(self) -> None:
        self.tree, self.words = prefix_tree(self.lexicon)

    def with_lexicon(self, lexicon: list[tuple[str, str]]) -> Decoder:
        return Decoder(lexicon, self.lm, self.back, self.order, self.beam, self.max_active, self.weight, self.floor)

    def with_lm(self, lm: dict, back: dict, order: int) -> Decoder:
        return Decoder(self.lexicon, lm, back, order, self.beam, self.max_active, self.weight, self.floor)

    def word_score(self, history: tuple[str, ...], word: str) -> float:
        h = history[max(0, len(history) - self.order + 1) :] if self.order > 1 else ()
        cost = 0.0
        while True:
            if (p := self.lm.get((*h, word))) is not None:
                return cost + p
            if not h:
                return cost + self.floor
            cost += self.back.get(h, 0.0)
            h = h[1:]

    def decode(self, frames: list[dict[str, float]], n: int = 1) -> list[tuple[tuple[str, ...], float]]:
        """frames: symbol -> log probability; symbols that a frame lacks have none. The n best word strings."""
        # token: (tree node, last symbol, words) -> score
        tokens: dict[tuple[int, str, tuple[str, ...]], float] = {(0, "_", ()): 0.0}
        for frame in frames:
            new: dict[tuple[int, str, tuple[str, ...]], float] = {}

            def put(key: tuple, score: float, new: dict = new) -> None:
                if score > new.get(key, -math.inf):
                    new[key] = score

            for (node, last, words), score in tokens.items():
                for sym, lp in frame.items():
                    if sym == "_":
                        put((node, "_", words), score + lp)
                    elif sym == last:
                        put((node, sym, words), score + lp)
                    elif (to := self.tree[node].get(sym)) is not None:
                        put((to, sym, words), score + lp)
                        for w in self.words[to]:
                            put((0, sym, (*words, w)), score + lp + self.weight * self.word_score(words, w))
            best = max(new.values(), default=0.0)
            kept = heapq.nlargest(self.max_active, ((s, k) for k, s in new.items() if s >= best - self.beam), key=lambda x: x[0])
            tokens = {k: s for s, k in kept}
            if not tokens:
                return [((), -math.inf)]
        ends: dict[tuple[str, ...], float] = {}
        for (node, _, words), score in tokens.items():
            if node == 0:
                ends[words] = max(ends.get(words, -math.inf), score + self.weight * (self.word_score(words, "</s>") if self.order > 1 else 0.0))
        if not ends:  # no word ended with the frames: what was complete before
            for (_, _, words), score in tokens.items():
                ends[words] = max(ends.get(words, -math.inf), score)
        return sorted(ends.items(), key=lambda x: -x[1])[:n]


def _find(keys: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of keys in a sorted array, and which are in it."""
    if not len(keys):
        return np.zeros(len(key), np.int64), np.zeros(len(key), bool)
    place = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
    return place, keys[place] == key


def _ranks(ids: np.ndarray, v: int) -> np.ndarray:
    """A number for each row of word numbers, in the rows' order, equal rows alike."""
    code = ids[:, 0].astype(np.int64)
    for j in range(1, ids.shape[1]):
        code = np.unique(code * v + ids[:, j], return_inverse=True)[1].reshape(-1)
    return code


class WordModel:
    """A back-off model's states as sorted arrays of numbers, a state for each context, in the order of length and words.

    ``contexts(k)``: word numbers (rows x k) of the contexts of k words, once each, and the logarithms of their weights;
    ``grams(n)``: word numbers (rows x n) and log probabilities, all of whose contexts are among those. Each is asked for
    once and let go, so that a model of millions takes its arrays and little more. Prefixes of contexts become contexts,
    and a context is reached by an arc: where its own words were not seen together, by one that costs what backing off does.
    """

    def __init__(self, vocabulary: list[str], order: int, contexts: Callable, grams: Callable, floor: float = math.log(1e-7)):
        self.vocabulary, self.order, self.floor = vocabulary, order, floor
        number = {w: i for i, w in enumerate(vocabulary)}
        v = self.v = len(vocabulary)
        self.end = number["</s>"]
        levels = [contexts(k) for k in range(1, order)]
        for k in range(len(levels) - 1, 0, -1):
            (ids, logs), prefix = levels[k - 1], levels[k][0][:, :k]
            both = np.concatenate([ids, prefix[np.unique(_ranks(prefix, v), return_index=True)[1]] if len(prefix) else prefix])
            first = np.unique(_ranks(both, v), return_index=True)[1] if len(both) else np.zeros(0, np.int64)
            levels[k - 1] = both[first], np.concatenate([logs, np.zeros(len(both) - len(ids))])[first]
        #: Keys of states, parent times v and word: state i + 1 is at place i, levels one after the other.
        self._states, self.back, edge = np.zeros(0, np.int64), np.zeros(1), [0, 1]
        for k in range(1, order):
            ids, logs = levels[k - 1]
            levels[k - 1] = None
            key = self._walk(ids[:, :-1]) * v + ids[:, -1]
            at = np.argsort(key)
            self._states, self.back = np.concatenate([self._states, key[at]]), np.concatenate([self.back, logs[at]])
            edge.append(len(self.back))
            del ids, logs, key, at
        self.n_states = len(self.back)
        self.back_to = np.zeros(self.n_states, np.int32)
        for k in range(2, order):
            key = self._states[edge[k] - 1 : edge[k + 1] - 1]
            self.back_to[edge[k] : edge[k + 1]] = self._next(self.back_to[key // v].astype(np.int64), key % v)
        place, hit = _find(self._states, np.array([number.get("<s>", -1)]))
        self.start = int(place[0]) + 1 if hit[0] else 0
        self.lm_key, self.lm_p, self.lm_to = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int32)
        for n in range(1, order + 1):
            ids, p = grams(n)
            state = self._walk(ids[:, :-1])
            word = ids[:, -1].astype(np.int64)
            key, to = state * v + word, self._next(state, word).astype(np.int32)
            del ids, state, word
            if n < order:
                own = np.arange(edge[n], edge[n + 1])
                own = own[~np.isin(self._states[own - 1], key) & (own != self.start)]
                lost = self._states[own - 1]
                key, to = np.concatenate([key, lost]), np.concatenate([to, own.astype(np.int32)])
                p = np.concatenate([p, self.word_scores(lost // v, lost % v)[0]])
            at = np.argsort(key)
            self.lm_key, self.lm_p, self.lm_to = np.concatenate([self.lm_key, key[at]]), np.concatenate([self.lm_p, p[at]]), np.concatenate([self.lm_to, to[at]])
            del key, p, to, at
        del self._states

    def _walk(self, ids: np.ndarray) -> np.ndarray:
        state = np.zeros(len(ids), np.int64)
        for j in range(ids.shape[1]):
            place, hit = _find(self._states, state * self.v + ids[:, j])
            if not hit.all():
                raise ValueError("an n-gram's context is not among the contexts")
            state = place + 1
        return state

    def _next(self, state: np.ndarray, word: np.ndarray) -> np.ndarray:
        """The longest known end of each state's words and the word."""
        out, at, todo = np.zeros(len(word), np.int64), state.copy(), np.arange(len(word))
        while len(todo):
            place, hit = _find(self._states, at[todo] * self.v + word[todo])
            out[todo[hit]] = place[hit] + 1
            todo = todo[~hit]
            todo = todo[at[todo] > 0]
            at[todo] = self.back_to[at[todo]]
        return out

    @classmethod
    def of(cls, decoder: Decoder) -> WordModel:
        """From a decoder's dictionaries."""
        order = max(decoder.order, 1)
        model = {k: p for k, p in decoder.lm.items() if len(k) <= order}
        contexts = {k[:-1] for k in model} | {k for k in decoder.back if len(k) < order}
        words = sorted({w for ws in decoder.words for w in ws} | {w for k in [*model, *contexts] for w in k} | {"</s>"})
        number = {w: i for i, w in enumerate(words)}

        def rows(table: dict, size: int) -> tuple[np.ndarray, np.ndarray]:
            found = [k for k in table if len(k) == size]
            return np.array([[number[w] for w in k] for k in found], np.int64).reshape(len(found), size), np.array([table[k] for k in found], float)

        weights = {k: decoder.back.get(k, 0.0) for k in contexts}
        return cls(words, order, lambda k: rows(weights, k), lambda n: rows(model, n), decoder.floor)

    def word_scores(self, state: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Log probability of each word after each state, backing off as often as it takes, and the state it leads to."""
        score, to, cost, at, todo = np.zeros(len(word)), np.zeros(len(word), np.int64), np.zeros(len(word)), state.copy(), np.arange(len(word))
        while len(todo):
            place, hit = _find(self.lm_key, at[todo] * self.v + word[todo])
            score[todo[hit]], to[todo[hit]] = cost[todo[hit]] + self.lm_p[place[hit]], self.lm_to[place[hit]]
            todo = todo[~hit]
            lost = at[todo] == 0
            score[todo[lost]] = cost[todo[lost]] + self.floor
            todo = todo[~lost]
            cost[todo] += self.back[at[todo]]
            at[todo] = self.back_to[at[todo]]
        return score, to


class Tree:
    """A lexicon's prefix tree as arrays; words are numbers in ``vocabulary``."""

    def __init__(self, tree: list[dict[str, int]], words: list[list[str]], vocabulary: list[str]):
        letters = sorted({c for node in tree for c in node} - {"_"})
        self.symbols = {"_": 0} | {c: i + 1 for i, c in enumerate(letters)}
        self.n_symbols, self.n_nodes = len(self.symbols) + 1, len(tree)  # the last one stands for symbols of no word
        arcs = sorted((n * self.n_symbols + self.symbols[c], to) for n, node in enumerate(tree) for c, to in node.items())
        self.child_key, self.child = (np.array(x, np.int64) for x in (zip(*arcs) if arcs else ((), ())))
        number = {w: i for i, w in enumerate(vocabulary)}
        self.word_first = np.cumsum([0, *map(len, words)])
        self.word = np.array([number[w] for ws in words for w in ws], np.int64)
        self._index()

    @classmethod
    def of(cls, ids: np.ndarray, sounds: list[str]) -> Tree:
        """From numbers of words and what they sound like, without a dictionary a node: nodes are made length by length."""
        self = cls.__new__(cls)
        size = np.array([len(s) for s in sounds], np.int64)
        flat = np.frombuffer("".join(sounds).encode("utf-32-le"), np.uint32)
        letters, code = np.unique(flat, return_inverse=True)
        letters = [chr(c) for c in letters.tolist()]
        self.symbols = {"_": 0} | {c: i + 1 for i, c in enumerate(c for c in letters if c != "_")}
        self.n_symbols, self.n_nodes = len(self.symbols) + 1, 1
        code = np.array([self.symbols[c] for c in letters], np.int64)[code.reshape(-1)] if letters else np.zeros(0, np.int64)
        begin, node, live, keys = np.cumsum(size) - size, np.zeros(len(size), np.int64), np.nonzero(size)[0], []
        for at in range(int(size.max(initial=0))):
            live = live[size[live] > at]
            key, child = np.unique(node[live] * self.n_symbols + code[begin[live] + at], return_inverse=True)
            node[live] = self.n_nodes + child.reshape(-1)
            self.n_nodes += len(key)
            keys.append(key)
        self.child_key = np.concatenate([*keys, np.zeros(0, np.int64)])  # in order, as nodes are
        self.child = np.arange(1, self.n_nodes)
        said = np.nonzero(size)[0]
        said = said[np.argsort(node[said], kind="stable")]
        self.word, self.word_first = np.asarray(ids, np.int64)[said], np.searchsorted(node[said], np.arange(self.n_nodes + 1))
        self._index()
        return self

    def _index(self) -> None:
        node = self.child_key // self.n_symbols
        self.child_first = np.searchsorted(node, np.arange(self.n_nodes))
        self.child_mask = np.zeros(self.n_nodes, np.uint64)  # a bit for each symbol that leads on, where they fit
        if self.n_symbols <= 64:
            np.bitwise_or.at(self.child_mask, node, np.uint64(1) << (self.child_key % self.n_symbols).astype(np.uint64))

    def step(self, node: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The node that each symbol leads to, and whether there is one."""
        if not len(self.child):
            return np.zeros(len(node), np.int64), np.zeros(len(node), bool)
        if self.n_symbols > 64:
            place, hit = _find(self.child_key, node * self.n_symbols + symbol)
            return self.child[place], hit
        bit = np.uint64(1) << symbol.astype(np.uint64)
        mask = self.child_mask[node]
        place = self.child_first[node] + np.bitwise_count(mask & (bit - np.uint64(1)))
        return self.child[np.minimum(place, len(self.child) - 1)], (mask & bit) != 0


class Graph:
    """A decoder as arrays: the lexicon's tree and the language model's states, searched for many clips at once.

    Tokens of one clip that share tree node, last symbol and language-model state are one: what follows costs them the same.
    """

    def __init__(self, decoder: Decoder):
        model = WordModel.of(decoder)
        self._set(Tree(decoder.tree, decoder.words, model.vocabulary), model, decoder.order, decoder.beam, decoder.max_active, decoder.weight)

    @classmethod
    def join(cls, tree: Tree, model: WordModel, beam: float, max_active: int, weight: float) -> Graph:
        graph = cls.__new__(cls)
        graph._set(tree, model, model.order, beam, max_active, weight)
        return graph

    def _set(self, tree: Tree, model: WordModel, order: int, beam: float, most: int, weight: float) -> None:
        self.order, self.beam, self.most, self.weight = order, beam, most, weight
        self.symbols, self.n_symbols, self.n_nodes = tree.symbols, tree.n_symbols, tree.n_nodes
        self.step, self.word_first, self.word = tree.step, tree.word_first, tree.word
        self.vocabulary, self.end, self.start, self.n_states, self.word_scores = model.vocabulary, model.end, model.start, model.n_states, model.word_scores
        #: No word's score is above this.
        self.highest = max(0.0, model.floor, model.lm_p.max(initial=-np.inf)) + (model.order - 1) * max(0.0, float(model.back.max(initial=0.0)))
        self.gain, self.tree, self.model = None, tree, model
        if model.n_states == 1:  # no history: words of one node lead to one token, so only its likeliest counts
            gain = self.word_scores(np.zeros(len(self.word), np.int64), self.word)[0]
            node = np.repeat(np.arange(self.n_nodes), np.diff(self.word_first))
            at = np.lexsort((-gain, node))
            at = at[np.diff(node[at], prepend=-1) != 0]
            self.word, self.gain = self.word[at], gain[at]
            self.word_first = np.searchsorted(node[at], np.arange(self.n_nodes + 1))

    def decode(self, clip: np.ndarray, t: np.ndarray, sym: np.ndarray, logp: np.ndarray, n: int) -> list[tuple[tuple[str, ...], float]]:
        """The likeliest words of ``n`` clips, whose frames' symbols are rows (clip, t from 0, symbol, log probability)."""
        length = np.zeros(n, int)
        np.maximum.at(length, clip, t + 1)
        order = np.lexsort((clip, t))
        clip, t, sym, logp = clip[order], t[order], sym[order], logp[order]
        edge = np.searchsorted(t, np.arange(length.max(initial=0) + 1))
        u, node, last, state = np.arange(n), np.zeros(n, np.int64), np.zeros(n, np.int64), np.full(n, self.start)
        history, score = np.full(n, -1), np.zeros(n)
        parents, spoken, made = [], [], 0  # histories: the one before and the word
        result: list[tuple[tuple[str, ...], float]] = [((), 0.0 if not length[i] else -np.inf) for i in range(n)]
        ends: dict[int, tuple[int, float]] = {}
        for now in range(length.max(initial=0)):
            rows = slice(edge[now], edge[now + 1])
            first = np.searchsorted(clip[rows], np.arange(n + 1)) + edge[now]
            count = (first[1:] - first[:-1])[u]
            token = np.repeat(np.arange(len(u)), count)
            at = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(first[u], count)
            s, value = sym[at], score[token] + logp[at]
            stay = (s == 0) | (s == last[token])
            bound = np.full(n, -np.inf)  # what stays is kept or beaten: nothing that is the beam below it is followed
            np.maximum.at(bound, u[token[stay]], value[stay])
            near = value >= bound[u[token]] - self.beam - self.weight * self.highest
            token, s, value, stay = token[near], s[near], value[near], stay[near]
            to, move = self.step(node[token], s)
            move &= ~stay
            to = np.where(stay, node[token], to)
            keep = stay | move
            token, s, value, to, move = token[keep], s[keep], value[keep], to[keep], move[keep]
            n_words = np.where(move, self.word_first[to + 1] - self.word_first[to], 0)
            said = np.repeat(np.arange(len(to)), n_words)
            place = np.arange(len(said)) - np.repeat(np.cumsum(n_words) - n_words, n_words) + np.repeat(self.word_first[to], n_words)
            word = self.word[place]
            gain, after = self.word_scores(state[token[said]], word) if self.gain is None else (self.gain[place], np.zeros(len(said), np.int64))
            c_token, c_node = np.concatenate([token, token[said]]), np.concatenate([to, np.zeros(len(said), np.int64)])
            c_last, c_state = np.concatenate([s, s[said]]), np.concatenate([state[token], after])
            c_word, c_score = np.concatenate([np.full(len(token), -1), word]), np.concatenate([value, value[said] + self.weight * gain])
            c_u = u[c_token]
            best = np.full(n, -np.inf)
            np.maximum.at(best, c_u, c_score)
            near = np.nonzero(c_score >= best[c_u] - self.beam)[0]
            key = ((c_u[near] * self.n_nodes + c_node[near]) * self.n_symbols + c_last[near]) * self.n_states + c_state[near]
            # the best of each key: single sorts of numbers, which are much faster than sorts by two
            order = np.argsort(key)
            first_of = np.diff(key[order], prepend=-1) != 0
            group, value = np.cumsum(first_of) - 1, c_score[near][order]
            top = np.nonzero(value == np.maximum.reduceat(value, np.nonzero(first_of)[0])[group])[0]
            near = near[order[top[np.diff(group[top], prepend=-1) != 0]]]
            near = near[np.argsort(c_u[near] * 1e6 - (c_score[near] - best[c_u[near]]))]
            rank = np.arange(len(near)) - np.searchsorted(c_u[near], np.arange(n + 1))[c_u[near]]
            near = near[rank < self.most]
            fresh = c_word[near] >= 0
            before = history[c_token[near]]
            ids = np.where(fresh, made + np.cumsum(fresh) - 1, before)
            parents.append(before[fresh])
            spoken.append(c_word[near][fresh])
            made += int(fresh.sum())
            u, node, last, state, history, score = c_u[near], c_node[near], c_last[near], c_state[near], ids, c_score[near]
            done = length[u] == now + 1
            if done.any():
                final = score.copy()
                if self.order > 1:
                    final += self.weight * self.word_scores(state, np.full(len(state), self.end))[0]
                whole = np.zeros(n, bool)
                whole[u[done & (node == 0)]] = True  # else no word ends with the frames: what was complete before
                final = np.where(whole[u], np.where(node == 0, final, -np.inf), score)
                pick = np.nonzero(done)[0]
                pick = pick[np.lexsort((-final[pick], u[pick]))]
                for i in pick[np.diff(u[pick], prepend=-1) != 0].tolist():
                    ends[int(u[i])] = (int(history[i]), float(final[i]))
                going = ~done
                u, node, last, state, history, score = u[going], node[going], last[going], state[going], history[going], score[going]
        parent, word = np.concatenate(parents or [np.zeros(0, int)]), np.concatenate(spoken or [np.zeros(0, int)])
        for i, (h, value) in ends.items():
            words = []
            while h >= 0:
                words.append(self.vocabulary[word[h]])
                h = int(parent[h])
            result[i] = (tuple(words[::-1]), value)
        return result


CLIPS_AT_ONCE = 64


#: Bytes of a row, and rows of a file, of an object on its way to the driver.
PIECE_BYTES, PIECES_A_FILE = 4 << 20, 2
#: Arrays of fewer bytes travel with the rest of their object.
SMALL = 1 << 16
#: That rest's name beside those of arrays.
REST = "(rest)"
#: Arrays that the driver reads at a time: four take more than its memory (1,713 MB on check_s).
ARRAYS_AT_ONCE = 1


class _Streamed(Broadcast):
    """A broadcast of bytes that are written to its file piece by piece, as a pickle whose bytes begin at ``HEAD``."""

    HEAD = 16

    def dump(self, value: tuple[int, Iterator[tuple[int, bytes]]], f: BinaryIO) -> None:
        size, parts = value
        f.write(b"\x80\x04K\x000N0\x8e" + size.to_bytes(8, "little"))  # a number and a None that are dropped again, for the length
        for at, data in parts:
            f.seek(self.HEAD + at)
            f.write(data)
        f.seek(self.HEAD + size)
        f.write(b".")
        f.close()


@dataclass
class Mapped:
    """A broadcast array: a file that the tasks of an executor map into their memory together."""

    cast: Broadcast
    dtype: str
    n: int

    @classmethod
    def of(cls, rows: DataFrame, name: str, dtype: str, n: int, more: list[tuple[str, int, np.ndarray]] = ()) -> Mapped:
        """From rows (name, at: byte, data) and ``more`` of them by element. The driver has a few rows of them at a time."""
        context, size = rows.sparkSession.sparkContext, n * np.dtype(dtype).itemsize
        parts = ((r["at"], r["data"]) for r in rows.where(F.col("name") == name).select("at", "data").toLocalIterator())
        parts = chain(((at * x.itemsize, x.tobytes()) for _, at, x in more), parts)
        if context._encryption_enabled:
            data = bytearray(size)
            for at, piece in parts:
                data[at : at + len(piece)] = piece
            return cls(context.broadcast(bytes(data)), dtype, n)
        return cls(_Streamed(context, (size, parts), context._pickled_broadcast_vars), dtype, n)

    @classmethod
    def several(cls, rows: DataFrame, arrays: dict[str, tuple]) -> dict[str, Mapped]:
        """name -> (type, size, more): some of them at a time, as each is read by one thread."""
        with ThreadPoolExecutor(ARRAYS_AT_ONCE) as pool:
            made = {n: pool.submit(cls.of, rows, n, *x) for n, x in arrays.items()}
            return {n: x.result() for n, x in made.items()}

    @classmethod
    def sent(cls, context: SparkContext, x: np.ndarray) -> Mapped:
        """An array that the driver has."""
        data = np.ascontiguousarray(x).view(np.uint8).data if len(x) else b""
        cast = context.broadcast(bytes(data)) if context._encryption_enabled else _Streamed(context, (len(data), iter([(0, data)])), context._pickled_broadcast_vars)
        return cls(cast, x.dtype.str, len(x))

    @property
    def value(self) -> np.ndarray:
        path = self.cast.__dict__.get("_path")
        if not self.n or path is None or (self.cast._sc is not None and self.cast._sc._encryption_enabled):
            return np.frombuffer(self.cast.value, self.dtype) if self.n else np.zeros(0, self.dtype)
        return np.asarray(np.memmap(path, self.dtype, "r", _Streamed.HEAD, (self.n,)))


@dataclass
class Pieces:
    """An object whose large arrays are broadcast one by one."""

    rest: Broadcast
    arrays: dict[str, Mapped]

    @property
    def value(self) -> object:
        kind, fields = self.rest.value
        out = kind.__new__(kind)
        out.__dict__.update(fields)
        out.__dict__.update({k: b.value for k, b in self.arrays.items()})
        return out


def pieces(rows: DataFrame, build: Callable[[Iterator[pa.RecordBatch]], object], name: str) -> Pieces:
    """The object that ``build`` makes of all rows, which are bounded, in one task. The driver has one array of it at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = build(batches)
        fields = dict(made.__dict__)
        large = {k: fields.pop(k) for k, x in list(fields.items()) if isinstance(x, np.ndarray) and x.nbytes >= SMALL}
        parts = {REST: ("", memoryview(pickle.dumps((type(made), fields))))} | {k: (x.dtype.str, np.ascontiguousarray(x).view(np.uint8).data) for k, x in large.items()}
        for k, (dtype, data) in parts.items():
            for at in range(0, len(data), PIECE_BYTES):
                yield pa.RecordBatch.from_pydict({"name": [k], "dtype": [dtype], "size": pa.array([len(data)], pa.int64()), "at": pa.array([at], pa.int64()), "data": pa.array([bytes(data[at : at + PIECE_BYTES])], pa.binary())})

    kind = "name string, dtype string, size long, at long, data binary"
    found = written(rows.repartition(1).mapInArrow(run, kind), name, by="name", maxRecordsPerFile=PIECES_A_FILE)
    context = rows.sparkSession.sparkContext
    sent = {r["name"]: (r["dtype"], r["size"]) for r in found.select("name", "dtype", "size").distinct().collect()}  # a row an array
    if REST not in sent:  # no rows, no task
        made = build(iter(()))
        return Pieces(context.broadcast((type(made), made.__dict__)), {})
    rest = bytearray(sent.pop(REST)[1])
    for part in found.where(F.col("name") == REST).select("at", "data").toLocalIterator():
        rest[part["at"] : part["at"] + len(part["data"])] = part["data"]
    arrays = Mapped.several(found, {k: (dtype, size // np.dtype(dtype).itemsize) for k, (dtype, size) in sent.items()})
    dropped(found)
    return Pieces(context.broadcast(pickle.loads(rest)), arrays)


@dataclass
class Shared:
    """A graph whose tree and word model are broadcast apart: what several methods have in common is sent once."""

    tree: Broadcast | Pieces
    model: Broadcast | Pieces
    beam: float
    max_active: int
    weight: float

    @property
    def value(self) -> Graph:
        return Graph.join(self.tree.value, self.model.value, self.beam, self.max_active, self.weight)


def _search(graph: Graph, lists: pa.Array) -> list[tuple[tuple[str, ...], float]]:
    """The likeliest words of clips given as lists of (t, sym, p)."""
    clip = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
    rows = lists.flatten()
    t, p = rows.field("t").to_numpy(zero_copy_only=False).astype(np.int64), rows.field("p").to_numpy(zero_copy_only=False)
    coded = rows.field("sym").dictionary_encode()
    table = np.array([graph.symbols.get(x, graph.n_symbols - 1) for x in coded.dictionary.to_pylist()], np.int64)
    sym = table[coded.indices.to_numpy()] if len(table) else np.zeros(0, np.int64)
    # frames are numbered from 0 in each clip, equal symbols of a frame added
    low = t.min(initial=0)
    span = t.max(initial=0) - low + 1
    frames, place = np.unique(clip * span + t - low, return_inverse=True)
    owner = frames // span
    frame = np.arange(len(frames)) - np.searchsorted(owner, np.arange(len(lists)))[owner]
    distinct, inverse = np.unique(place.reshape(-1) * graph.n_symbols + sym, return_inverse=True)
    total = np.bincount(inverse.reshape(-1), weights=p, minlength=len(distinct))
    of = distinct // graph.n_symbols
    return graph.decode(owner[of], frame[of], distinct % graph.n_symbols, np.log(np.maximum(total, 1e-300)), len(lists))


def clip_decode(clips: DataFrame, graph: Broadcast | Shared, rows: str = "rows") -> DataFrame:
    """clips with ``rows`` (array of t, sym, p) -> the other columns and words, score. A clip is a row: nothing is shuffled."""
    names = [c for c in clips.columns if c != rows]
    types = dict(clips.dtypes)

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Graph = graph.value
        for whole in batches:
            # clips of like length are searched together, so that no frame is left with a few
            order = np.argsort(np.diff(whole.column(len(names)).offsets.to_numpy()), kind="stable")
            for start in range(0, whole.num_rows, CLIPS_AT_ONCE):
                b = whole.take(pa.array(order[start : start + CLIPS_AT_ONCE]))
                out = _search(found, b.column(len(names)))
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([list(w) for w, _ in out], pa.list_(pa.string())), pa.array([x for _, x in out], pa.float64())], names=[*names, "words", "score"])

    return clips.select(*names, rows).mapInArrow(best, ", ".join(f"{c} {types[c]}" for c in names) + ", words array<string>, score double")


def fst_decode(lattice: DataFrame, decoder: Decoder, keys: list[str], n: int = 1) -> DataFrame:
    """lattice (keys, t, sym, p) -> keys, rank, words, score. The graph is broadcast, each clip is searched in one task.

    The best string comes from the array search; the n best from the search that keeps word strings apart.
    """
    spark: SparkSession = lattice.sparkSession
    cast = spark.sparkContext.broadcast(Graph(decoder) if n == 1 else decoder)
    clips = lattice.groupBy(*keys).agg(F.collect_list(F.struct("t", "sym", "p")).alias("rows"))
    if n == 1:
        return clip_decode(clips, cast).select(*keys, F.lit(0).alias("rank"), "words", "score")
    types = dict(lattice.dtypes)
    schema = ", ".join(f"{k} {types[k]}" for k in keys) + ", rank int, words array<string>, score double"

    def several(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for row in b.itertuples(index=False):
                frames: dict[int, dict[str, float]] = defaultdict(dict)
                for x in row.rows:
                    lp = float(np.log(max(x["p"], 1e-300)))
                    frames[x["t"]][x["sym"]] = float(np.logaddexp(frames[x["t"]].get(x["sym"], -np.inf), lp))
                for rank, (words, score) in enumerate(cast.value.decode([frames[t] for t in sorted(frames)], n)):
                    out.append((*row[: len(keys)], rank, list(words), score))
            yield pd.DataFrame(out, columns=[*keys, "rank", "words", "score"])

    return clips.mapInPandas(several, schema)

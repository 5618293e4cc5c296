"""The pairwise model of one canopy, worked out row by row in numpy where a chain needs it.

A row holds the weights of one mention with all others, by the same features as functions.features: what two strings
say is worked out once per pair of distinct strings, what contexts say by posting lists of their words.  Rows are
kept up to a bound and made anew beyond it, so that the model is the same at every size and no pair is ever stored
or shuffled.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np

from erfocus.functions.features import FeatureSpec
from erfocus.functions.strings import py_qgrams

KEEP_BYTES = 256 << 20
#: Features that two strings decide, and those that contexts and keywords decide.
OF_STRINGS = ("f01", "f02", "f03", "f04", "f05", "f06", "f07", "f09", "f13")
OF_CONTEXTS = ("f10", "f11", "f12", "f14")


@dataclass
class Sides:
    """Mentions of a canopy in the order of their ids: strings and tokens by distinct string, contexts as lists of term numbers.

    Of n_terms words only those that are a token or keyword of a mention are known by name (terms), as no feature asks for
    others' names.  Numbers of words, which are most of it, are pickled by their differences.
    """

    ids: np.ndarray
    docs: np.ndarray
    strings: list[str]
    sid: np.ndarray
    toks: list[tuple[str, ...]]
    n_terms: int
    terms: dict[int, str]
    ptr: np.ndarray
    cid: np.ndarray
    kw: dict[int, tuple[str, ...]]

    def __getstate__(self) -> dict:
        return self.__dict__ | {"cid": squeezed(self.cid, self.ptr)}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state | {"cid": expanded(state["cid"], state["ptr"])})

    @classmethod
    def of(cls, ids, docs, ms, toks, ctxs, kws) -> Sides:
        """The same from lists; words of contexts may be anything that is equal where words are."""
        number: dict[str, int] = {}
        terms: dict[str, int] = {}
        own: list[tuple[str, ...]] = []
        sid, cid, ptr, kw = [], [], [0], {}
        for i, (m, t, ctx, k) in enumerate(zip(ms, toks, ctxs, kws, strict=True)):
            if m not in number:
                number[m] = len(number)
                own.append(tuple(t))
            sid.append(number[m])
            cid.extend(sorted({terms.setdefault(x, len(terms)) for x in ctx}))
            ptr.append(len(cid))
            if len(k):
                kw[i] = tuple(k)
        return cls(np.asarray(ids, dtype=np.int64), np.asarray(docs), list(number), np.array(sid, dtype=np.int64), own, len(terms), {k: t for t, k in terms.items() if isinstance(t, str)}, np.array(ptr, dtype=np.int64), np.array(cid, dtype=np.int32), kw)

    @classmethod
    def of_table(cls, table) -> Sides:
        """The same from Arrow columns mention_id, doc_id, m, toks, ctx, kw, sorted by mention_id, without a Python object a mention."""
        import pyarrow.compute as pc

        ctx = table["ctx"].combine_chunks()
        owner, words = np.asarray(pc.list_parent_indices(ctx)), pc.list_flatten(ctx).dictionary_encode()
        # Words of a mention once each and in the order of their numbers.
        both = np.unique(owner.astype(np.int64) * max(len(words.dictionary), 1) + words.indices.to_numpy())
        owner, cid = np.divmod(both, max(len(words.dictionary), 1))
        return cls.of_numbers(table, words.dictionary, np.bincount(owner, minlength=table.num_rows), cid.astype(np.int32))

    @classmethod
    def of_numbers(cls, table, words, size: np.ndarray, cid: np.ndarray) -> Sides:
        """The same from Arrow columns mention_id, doc_id, m, toks, kw, distinct words, and of each mention how many it has and their numbers."""
        import pyarrow as pa
        import pyarrow.compute as pc

        m = table["m"].combine_chunks().dictionary_encode()
        sid = m.indices.to_numpy().astype(np.int64)
        _, first = np.unique(sid, return_index=True)
        toks = [tuple(t) for t in table["toks"].take(pa.array(first)).to_pylist()]
        kws = table["kw"].combine_chunks()
        with_kw = np.flatnonzero(np.asarray(pc.list_value_length(kws)) > 0)
        kw = {int(i): tuple(x) for i, x in zip(with_kw, kws.take(pa.array(with_kw)).to_pylist(), strict=True)}
        asked = pa.array(sorted({x for own in (*toks, *kw.values()) for x in own}), pa.string())
        named = np.flatnonzero(np.asarray(pc.is_in(words, value_set=asked))) if len(words) else []
        terms = {int(k): words[int(k)].as_py() for k in named}
        ptr = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
        return cls(table["mention_id"].to_numpy(), table["doc_id"].to_numpy(), m.dictionary.to_pylist(), sid, toks, len(words), terms, ptr, cid, kw)

    def __len__(self) -> int:
        return len(self.ids)

    def some(self, rows: np.ndarray) -> Sides:
        """The mentions of some places, in their order."""
        ctx = [[self.terms.get(k, k) for k in self.cid[self.ptr[i] : self.ptr[i + 1]].tolist()] for i in rows]
        return Sides.of(self.ids[rows], self.docs[rows], [self.strings[self.sid[i]] for i in rows], [self.toks[self.sid[i]] for i in rows], ctx, [self.kw.get(int(i), ()) for i in rows])


def squeezed(cid: np.ndarray, ptr: np.ndarray) -> list[bytes]:
    """Rising numbers of each list, of non-negative int32, as compressed bytes of their differences, first all lowest ones."""
    step = np.diff(cid, prepend=np.int32(0))
    first = ptr[:-1][np.diff(ptr) > 0]
    step[first] = cid[first]
    planes = step.astype("<u4").view(np.uint8).reshape(-1, 4)
    return [zlib.compress(planes[:, k].tobytes(), 1) for k in range(4)]


def expanded(planes: list[bytes], ptr: np.ndarray) -> np.ndarray:
    step = np.empty((int(ptr[-1]), 4), dtype=np.uint8)
    for k, plane in enumerate(planes):
        step[:, k] = np.frombuffer(zlib.decompress(plane), dtype=np.uint8)
    out = step.view("<u4").reshape(-1).astype(np.int32)
    # A running sum over all lists, in which each list's first number starts anew.
    first = ptr[:-1][np.diff(ptr) > 0]
    last = np.add.reduceat(out, first, dtype=np.int64)[:-1] if len(first) else first
    out[first[1:]] -= last.astype(np.int32)
    return np.cumsum(out, dtype=np.int32, out=out)


class Rows:
    """Kept rows of weights; weigh(i) makes one."""

    def __init__(self, n: int, keep_bytes: int = KEEP_BYTES):
        self.n, self.most, self.known = n, max(1, keep_bytes // max(4 * n, 1)), {}

    def row(self, i: int) -> np.ndarray:
        found = self.known.get(i)
        if found is None:
            if len(self.known) >= self.most:
                self.known.clear()
            found = self.known[i] = self.weigh(i)
        return found

    def weigh(self, i: int) -> np.ndarray:
        raise NotImplementedError


class Dense(Rows):
    """Weights of all pairs, given."""

    def __init__(self, w: np.ndarray):
        super().__init__(len(w))
        self.w = w

    def row(self, i: int) -> np.ndarray:
        return self.w[i]


class PairModel(Rows):
    """Weights by features; cosines: the similarity tiers are of contexts' tf-idf cosine, else of strings' q-grams."""

    def __init__(self, specs: Iterable[FeatureSpec], sides: Sides, cosines: bool = True, keep_bytes: int = KEEP_BYTES):
        super().__init__(len(sides), keep_bytes)
        self.specs = tuple(s for s in specs if s.klass != "entity")
        self.sides, self.cosines = sides, cosines
        self.by_string: dict[int, np.ndarray] = {}
        self._strings()
        self._contexts()

    # what is made once

    def _strings(self) -> None:
        s = self.sides.strings
        code = lambda xs: np.unique(np.array(xs, dtype=object).astype(str), return_inverse=True)[1] if xs else np.zeros(0, dtype=np.int64)
        self.first, self.second, self.third = (code([x[k : k + 1] for x in s]) for k in range(3))
        self.has_second = np.array([len(x) > 1 for x in s], dtype=bool)
        self.length = np.array([len(x) for x in s], dtype=np.int64)
        self.lead = np.array([t[0] if t else "\0" for t in self.sides.toks] or [""], dtype=object)[: len(s)]
        self.tok_sets = [frozenset(t) for t in self.sides.toks]
        self.n_toks = np.array([len(t) for t in self.tok_sets], dtype=np.int64)
        self.tok_post: dict[str, list[int]] = {}
        for u, own in enumerate(self.tok_sets):
            for t in own:
                self.tok_post.setdefault(t, []).append(u)
        self.gram_sets = None

    def _grams(self) -> None:
        self.gram_sets = [py_qgrams(x) for x in self.sides.strings]
        self.n_grams = np.array([len(g) for g in self.gram_sets], dtype=np.int64)
        post: dict[str, list[int]] = {}
        for u, own in enumerate(self.gram_sets):
            for g in own:
                post.setdefault(g, []).append(u)
        self.gram_post = {g: np.array(us) for g, us in post.items()}

    #: Words that are dealt at once.
    DEAL = 4_000_000

    def _contexts(self) -> None:
        s, n = self.sides, len(self.sides)
        size = np.diff(s.ptr)
        df = np.bincount(s.cid, minlength=s.n_terms)
        self.idf = np.log(np.maximum(float(max((size > 0).sum(), 1)) / np.maximum(df, 1.0), 1.0))
        self.norm, self.post = np.zeros(n), np.empty(len(s.cid), dtype=np.int32)
        self.post_at = np.concatenate([[0], np.cumsum(df)]).astype(np.int64)
        # Postings are made from some mentions' words after the others', so that nothing but them is as long as all words.
        free, low = self.post_at[:-1].copy(), 0
        while low < n:
            high = max(low + 1, int(np.searchsorted(s.ptr, s.ptr[low] + self.DEAL, side="right")) - 1)
            cid, owner = s.cid[s.ptr[low] : s.ptr[high]], np.repeat(np.arange(high - low), size[low:high])
            self.norm[low:high] = np.sqrt(np.bincount(owner, weights=self.idf[cid] ** 2, minlength=high - low))
            order = np.argsort(cid, kind="stable")
            found, begin, many = np.unique(cid[order], return_index=True, return_counts=True)
            self.post[np.repeat(free[found] - begin, many) + np.arange(len(cid))] = owner[order] + low
            free[found] += many
            low = high
        self.has_vector = self.norm > 0
        self.term_of = {t: k for k, t in s.terms.items()}

    def _with_term(self, k: int) -> np.ndarray:
        return self.post[self.post_at[k] : self.post_at[k + 1]]

    # features of one mention with all

    def similarity(self, i: int) -> np.ndarray:
        """Cosines of i's context with all; nan where a side has no weighted word."""
        out = np.zeros(self.n)
        a, b = self.sides.ptr[i : i + 2]
        if not self.has_vector[i]:
            return np.full(self.n, np.nan)
        for k in self.sides.cid[a:b].tolist():
            if self.idf[k] > 0:
                near = self.post[self.post_at[k] : self.post_at[k + 1]]
                out[near] += self.idf[k] / self.norm[i] * (self.idf[k] / self.norm[near])
        out[~self.has_vector] = np.nan
        return out

    def text_similarity(self, u: int) -> np.ndarray:
        if self.gram_sets is None:
            self._grams()
        common = np.zeros(len(self.sides.strings), dtype=np.int64)
        for g in self.gram_sets[u]:
            common[self.gram_post[g]] += 1
        return common / (self.n_grams + self.n_grams[u] - common)

    def of_string(self, name: str, u: int) -> np.ndarray:
        """Whether a feature holds between string u and every string."""
        s = self.sides.strings
        if name == "f01":
            return np.arange(len(s)) == u
        if name == "f02":
            return self.first == self.first[u]
        if name == "f03":
            return (self.second == self.second[u]) & self.has_second[u]
        if name == "f04":
            return self.third == self.third[u]
        if name == "f05":
            return np.array([x in s[u] or s[u] in x for x in s], dtype=bool)
        if name == "f06":
            return self.length == self.length[u]
        if name == "f07":
            return (self.lead == self.lead[u]).astype(bool) & (self.n_toks > 0)
        common = np.zeros(len(s), dtype=np.int64)
        for t in self.tok_sets[u]:
            common[self.tok_post[t]] += 1
        if name == "f09":
            return common > 0
        if name == "f13":
            return (self.n_toks > common) & (self.n_toks[u] > common)
        raise KeyError(name)

    def of_context(self, name: str, i: int) -> np.ndarray:
        """Whether a feature holds between mention i and every mention."""
        s, out = self.sides, np.zeros(self.n, dtype=bool)
        own = s.cid[s.ptr[i] : s.ptr[i + 1]].tolist()
        if name == "f14":
            for k in own:
                out[self._with_term(k)] = True
        elif name == "f10":
            for t in self.tok_sets[s.sid[i]]:
                if t in self.term_of:
                    out[self._with_term(self.term_of[t])] = True
            with_tok = [u for k in own if k in s.terms for u in self.tok_post.get(s.terms[k], ())]
            if with_tok:
                out |= np.isin(s.sid, with_tok)
        elif name == "f11":
            for k in s.kw.get(i, ()):
                if k in self.term_of:
                    out[self._with_term(self.term_of[k])] = True
            here = {s.terms[k] for k in own if k in s.terms} if s.kw else ()
            for j, words in s.kw.items():
                out[j] |= any(k in here for k in words)
        elif name == "f12":
            m = s.strings[s.sid[i]]
            if i in s.kw:
                out |= np.array([any(k in x for k in s.kw[i]) for x in s.strings], dtype=bool)[s.sid]
            for j, words in s.kw.items():
                out[j] |= any(k in m for k in words)
        else:
            raise KeyError(name)
        return out

    def has_keywords(self, i: int) -> np.ndarray:
        """Whether either side has keywords."""
        out = np.full(self.n, i in self.sides.kw)
        out[list(self.sides.kw)] = True
        return out

    @staticmethod
    def tier_of(similarity: np.ndarray, spec: FeatureSpec) -> np.ndarray:
        """The number of the tier reached, from 0 for the lowest; -1 where there is no similarity."""
        edges = [least for least, _ in reversed(spec.tiers)]
        found = np.searchsorted(edges, np.round(np.nan_to_num(similarity), 9), side="right")
        return np.where(np.isnan(similarity), -1, found)

    @staticmethod
    def tier_weights(spec: FeatureSpec) -> np.ndarray:
        """Weights of tiers from the lowest; the last stands for none."""
        return np.array([spec.lowest, *(w for _, w in reversed(spec.tiers)), 0], dtype=np.int32)

    def string_row(self, u: int) -> np.ndarray:
        found = self.by_string.get(u)
        if found is None:
            if len(self.by_string) * len(self.sides.strings) * 4 > KEEP_BYTES // 4:
                self.by_string.clear()
            found = np.zeros(len(self.sides.strings), dtype=np.int32)
            for spec in self.specs:
                if spec.name in OF_STRINGS and (spec.plus or spec.minus):
                    plus, minus = (spec.minus, spec.plus) if spec.name == "f13" else (spec.plus, spec.minus)
                    found += np.where(self.of_string(spec.name, u), plus, minus).astype(np.int32)
                elif spec.name == "f08" and not self.cosines:
                    found += self.tier_weights(spec)[self.tier_of(self.text_similarity(u), spec)]
            self.by_string[u] = found
        return found

    def weigh(self, i: int) -> np.ndarray:
        u = int(self.sides.sid[i])
        out = self.string_row(u)[self.sides.sid].astype(np.int32)
        for spec in self.specs:
            if spec.name == "f08" and self.cosines:
                out += self.tier_weights(spec)[self.tier_of(self.similarity(i), spec)]
            elif spec.name == "f11" and self.sides.kw:
                out += np.where(self.has_keywords(i), np.where(self.of_context("f11", i), spec.plus, spec.minus), 0).astype(np.int32)
            elif spec.name in ("f10", "f12", "f14") and (spec.plus or spec.minus):
                out += np.where(self.of_context(spec.name, i), spec.plus, spec.minus).astype(np.int32)
        out[i] = 0
        return out

    def classes(self, most: int) -> tuple[list[int], np.ndarray] | None:
        """Each mention's class of those that no feature tells apart, and weights between classes; none where they are over most.

        A class' weight with itself is that of two of its mentions.
        """
        s, number, firsts, second, of = self.sides, {}, [], {}, []
        ptr, sid = s.ptr.tolist(), s.sid.tolist()
        for i in range(self.n):
            key = (sid[i], s.cid[ptr[i] : ptr[i + 1]].tobytes(), s.kw.get(i))
            k = number.setdefault(key, len(number))
            if k == len(firsts):
                if k == most:
                    return None
                firsts.append(i)
            else:
                second.setdefault(k, i)
            of.append(k)
        w = np.zeros((len(firsts), len(firsts)), dtype=np.int64)
        for k, i in enumerate(firsts):
            row = self.row(i)
            w[k] = row[firsts]
            w[k, k] = row[second[k]] if k in second else 0
        return of, w

    def own_weight(self, i: int) -> int:
        """What the features give a mention with itself: its influence on itself, though no weight of the model."""
        total = int(self.string_row(int(self.sides.sid[i]))[self.sides.sid[i]])
        for spec in self.specs:
            if spec.name == "f08" and self.cosines:
                total += int(self.tier_weights(spec)[self.tier_of(self.similarity(i)[i : i + 1], spec)][0])
            elif spec.name == "f11" and i in self.sides.kw:
                total += spec.plus if self.of_context("f11", i)[i] else spec.minus
            elif spec.name in ("f10", "f12", "f14"):
                total += spec.plus if self.of_context(spec.name, i)[i] else spec.minus
        return total

    def indicators(self, i: int) -> np.ndarray:
        """(features, n): for each feature two rows, that it holds and that it does not; for the similarity one a tier."""
        u, out = int(self.sides.sid[i]), []
        for spec in self.specs:
            if spec.name == "f08":
                reached = self.tier_of(self.similarity(i), spec) if self.cosines else self.tier_of(self.text_similarity(u), spec)[self.sides.sid]
                out += [reached == k for k in range(len(spec.tiers) + 1)]
                continue
            asked = self.has_keywords(i) if spec.name == "f11" else np.ones(self.n, dtype=bool)
            holds = self.of_string(spec.name, u)[self.sides.sid] if spec.name in OF_STRINGS else self.of_context(spec.name, i)
            out += [holds & asked, ~holds & asked]
        return np.stack(out)

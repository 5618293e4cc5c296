"""Chains as a DataFrame operator: one packed row per canopy, one task per (canopy, run)."""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Callable, Iterable
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.rand import py_h32
from erfocus.operators.alias import vose
from erfocus.operators.durable import held
from erfocus.operators.kernel import Biased, Budget, Chain, ClassChain, EntityFeatures, Query
from erfocus.operators.pairs import PairModel, Sides, expanded, squeezed
from erfocus.operators.schedule import QUANTUM, Turns

PACKED = "component long, n int, model binary"
RESULT = "component long, run_id int, mention_id long, entity_id long, step int, query_id long, kind string, m long, e_from long, e_to long, delta long, accepted boolean, seconds double"
#: Rows of a chain's state that are handed out at once.
SLICE = 50_000
#: Classes of mentions up to which a chain without a trace goes by classes.
MOST_CLASSES = 1000
WHOLE = 1_000_000


@dataclass(frozen=True)
class Settings:
    """What a chain is run with; see the kernel for the samplers.  'auto' sheds from one entity of all (expel) where most of
    a canopy is of positive influence on its query, and gathers (influence_to_query) elsewhere, component by component.

    until: a function of the last `every` rows of the trace that ends the chain when it is true (see converge); idle:
    ends it after so many proposals in a row without an accepted one.  cosines: whether similarity is of contexts.
    init: singletons, single, random or previous (what pack() was given); by default as the sampler wants it.
    matching: the weight of each pair of equal strings of an entity, with entity_wide.
    """

    sampler: str = "influence_to_query"
    tau: float = 0.9
    samples: int = 1000
    accept: str = "greedy"
    temperature: float = 1.0
    seed: int = 1
    init: str | None = None
    policy: str = "round_robin"
    quantum: int = QUANTUM
    draw: str = "alias"
    r: int = 1
    p: float = 0.05
    scaled: bool = True
    unit: str = "rank"
    idle: int | None = None
    until: Callable[[list], bool] | None = None
    every: int = 100
    entity_wide: bool = False
    matching: int = 0
    cosines: bool = True
    hold: bool | None = None


@dataclass
class Packed:
    """A component: its mentions, its queries as (query_id, own place, places of its canopy), labels to start from."""

    sides: Sides
    queries: list[tuple[int, int, np.ndarray]]
    start: np.ndarray | None


def pack(canopy: DataFrame, mentions: DataFrame, queries: DataFrame, components: DataFrame | None = None, level: str = "document", max_canopy: int | None = None, start: DataFrame | None = None) -> DataFrame:
    """A row per component of canopies: mentions with strings and contexts, and which of them each query's canopy has.

    canopy: (query_id, mention_id), queries' own mentions among them; components: (query_id, component), or each query
    for itself; start: (mention_id, entity_id) of an earlier result.  Weights and influence are worked out from this by
    the chain, so that no pair of mentions is shipped.  Components are whole at any size; where max_canopy is given, one of
    more members is refused: it is for the bulk-synchronous rounds.
    """
    own = queries.select("query_id", F.col("mention_id").alias("own"))
    owner = own if components is None else own.join(components, "query_id")
    owner = owner.withColumn("component", F.col("query_id")) if components is None else owner
    owner = held(owner.select("query_id", "own", "component"))
    # A mention meets its text once, whatever the number of canopies that it is in.
    members = canopy.select("query_id", "mention_id").join(owner.select("query_id", "component").distinct(), "query_id").groupBy("mention_id").agg(F.collect_set(F.struct("component", "query_id")).alias("at"))
    rows = features.prepare(mentions.select("mention_id", "doc_id", "mention", "context"), level, "side").join(held(members), "mention_id")
    if start is not None:
        rows = rows.join(start.select("mention_id", F.col("entity_id").alias("label")), "mention_id", "left")
    else:
        rows = rows.withColumn("label", F.lit(None).cast("long"))
    rows = rows.select("mention_id", F.coalesce("doc_id", "mention_id").alias("doc_id"), F.coalesce("side.m", F.lit("")).alias("m"), "side.toks", "side.ctx", "side.kw", F.coalesce("label", "mention_id").alias("label"), F.col("at.component").alias("component"), F.col("at.query_id").alias("query"))
    warm = start is not None

    def run(table, asked):
        import pyarrow as pa

        if not table.num_rows:
            return pa.table({"component": pa.array([], pa.int64()), "n": pa.array([], pa.int32()), "model": pa.array([], pa.binary())})
        whole, words, size, cid = _joined(table["slab"])
        if max_canopy is not None and len(whole) > max_canopy:
            raise ValueError(f"component {table['component'][0]} has {len(whole)} mentions; resolve it by rounds")
        sides = Sides.of_numbers(whole, words, size, cid)
        queries = whole["query"].combine_chunks()
        place, query = np.asarray(pa.compute.list_parent_indices(queries)), np.asarray(pa.compute.list_flatten(queries))
        at = np.searchsorted(sides.ids, asked["own"].to_numpy())
        own = {q: int(k) for q, o, k in zip(asked["query_id"].to_pylist(), asked["own"].to_pylist(), at, strict=True) if k < len(sides) and sides.ids[k] == o}
        order = np.argsort(query, kind="stable")
        ids, begins = np.unique(query[order], return_index=True)
        found = [(int(k), own.get(int(k)), p.astype(np.int64)) for k, p in zip(ids, np.split(place[order], begins[1:]), strict=True)]
        packed = Packed(sides, found, whole["label"].to_numpy() if warm else None)
        blob = zlib.compress(pickle.dumps(packed, protocol=5), 1)
        return pa.table({"component": table["component"].slice(0, 1), "n": pa.array([len(whole)], pa.int32()), "model": pa.array([blob], pa.binary())})

    # Few rows, but each a chain's work: they are dealt to a number of tasks that is given, not by their bytes.
    tasks = 4 * mentions.sparkSession.sparkContext.defaultParallelism
    slabs = rows.mapInArrow(_slabs, "component long, slab binary").repartition(tasks, "component")
    return slabs.groupBy("component").cogroup(owner.repartition(tasks, "component").groupBy("component")).applyInArrow(run, PACKED)


def _slabs(batches):
    """(component, slab): a batch's mentions of each component, distinct words once, mentions' words as squeezed numbers."""
    import pyarrow as pa
    import pyarrow.compute as pc

    for batch in batches:
        table = pa.Table.from_batches([batch]).sort_by("mention_id")
        ctx = table["ctx"].combine_chunks()
        words = pc.list_flatten(ctx).dictionary_encode()
        most = max(len(words.dictionary), 1)
        owner, cid = np.divmod(np.unique(np.asarray(pc.list_parent_indices(ctx)).astype(np.int64) * most + words.indices.to_numpy()), most)
        ptr = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=len(table)))]).astype(np.int64)
        at = table["component"].combine_chunks()
        row, component, query = np.asarray(pc.list_parent_indices(at)), np.asarray(pc.list_flatten(at)), np.asarray(pc.list_flatten(table["query"].combine_chunks()))
        flat = table.drop_columns(["ctx", "component", "query"])
        order = np.lexsort((query, row, component))
        row, component, query = row[order], component[order], query[order]
        begins = np.flatnonzero(np.diff(component, prepend=component[:1] - 1)) if len(component) else np.zeros(0, dtype=np.int64)
        for low, high in zip(begins, [*begins[1:], len(component)], strict=True):
            mine, first = np.unique(row[low:high], return_index=True)
            inside = np.repeat(ptr[mine], ptr[mine + 1] - ptr[mine])
            places = np.concatenate([[0], np.cumsum(ptr[mine + 1] - ptr[mine])]).astype(np.int64)
            taken = cid[inside + np.arange(len(inside)) - np.repeat(places[:-1], np.diff(places))]
            known, numbers = np.unique(taken, return_inverse=True)
            queries = pa.ListArray.from_arrays(pa.array([*first, high - low], pa.int32()), pa.array(query[low:high]))
            part = flat.take(pa.array(mine)).append_column("query", queries).append_column("size", pa.array(np.diff(places)))
            slab = (_arrow_bytes(part), _arrow_bytes(pa.table({"word": words.dictionary.take(pa.array(known))})), squeezed(numbers.reshape(-1).astype(np.int32), places))
            yield pa.RecordBatch.from_arrays([pa.array([component[low]]), pa.array([pickle.dumps(slab, protocol=5)], pa.binary())], names=["component", "slab"])


def _arrow_bytes(table) -> bytes:
    import pyarrow as pa

    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _joined(slabs):
    """(mentions in the order of their ids, distinct words, how many words each mention has, their numbers) of a component's slabs."""
    import pyarrow as pa

    read = lambda b: pa.ipc.open_stream(b).read_all()
    tables, words, lists = [], [], []
    for slab in slabs:
        part, word, planes = pickle.loads(slab.as_py())
        tables.append(read(part))
        words.append(read(word)["word"].combine_chunks())
        size = tables[-1]["size"].to_numpy()
        lists.append((size, expanded(planes, np.concatenate([[0], np.cumsum(size)]).astype(np.int64))))
    every = pa.chunked_array(words, pa.string()).dictionary_encode().unify_dictionaries()
    numbers = [c.indices.to_numpy().astype(np.int32) for c in every.chunks if len(c)]
    known = every.chunk(0).dictionary
    named = iter(numbers)
    whole, size = pa.concat_tables(tables), np.concatenate([x for x, _ in lists])
    cid = np.concatenate([next(named)[x] if len(x) else x for _, x in lists])
    # Mentions in the order of their ids, and each one's words in the order of their numbers.
    order = np.argsort(whole["mention_id"].to_numpy(), kind="stable")
    begin = (np.cumsum(size) - size)[order]
    size, out, at = size[order], np.empty_like(cid), 0
    for low in range(0, len(order), SLICE):
        many = size[low : low + SLICE]
        ends = np.cumsum(many)
        taken = cid[np.repeat(begin[low : low + SLICE] - (ends - many), many) + np.arange(many.sum())]
        both = np.sort(np.repeat(np.arange(len(many)), many) << 32 | taken)
        out[at : at + len(both)] = (both & 0xFFFFFFFF).astype(np.int32)
        at += len(both)
    return whole.take(pa.array(order)), known, size, out


def pack_blocks(mentions: DataFrame, key: Column, level: str = "document", max_canopy: int | None = None) -> DataFrame:
    """pack() of disjoint blocks of several mentions with equal keys, by one exchange of the mentions; nulls are in no block.

    A block's first mention names its component and is its query.
    """
    rows = features.prepare(mentions.withColumn("__b", key).select("__b", "mention_id", "doc_id", "mention", "context"), level, "side").where("__b IS NOT NULL")
    rows = rows.select("__b", "mention_id", F.coalesce("doc_id", "mention_id").alias("doc_id"), F.coalesce("side.m", F.lit("")).alias("m"), "side.toks", "side.ctx", "side.kw")
    rows = rows.withColumn("__n", F.count(F.lit(1)).over(Window.partitionBy("__b"))).where("__n > 1").drop("__n")

    def run(table):
        import pyarrow as pa

        table = table.sort_by("mention_id")
        n, first = table.num_rows, table["mention_id"].slice(0, 1)
        if max_canopy is not None and n > max_canopy:
            raise ValueError(f"component {first[0]} has {n} mentions; resolve it by rounds")
        whole = Packed(Sides.of_table(table), [(first[0].as_py(), 0, np.arange(n))], None)
        blob = zlib.compress(pickle.dumps(whole, protocol=5), 1)
        return pa.table({"component": first, "n": pa.array([n], pa.int32()), "model": pa.array([blob], pa.binary())})

    return rows.groupBy("__b").applyInArrow(run, PACKED)


def unpacked(blob: bytes) -> Packed:
    return pickle.loads(zlib.decompress(blob))


def edges(packed: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, cosines: bool = True) -> DataFrame:
    """(component, i, j, w) with i < j: the weights that chains over the packed components use, written out.

    As many rows as half the squares of the components' sizes: for small ones, and for checks.
    """
    specs = tuple(specs)

    def run(batches):
        for pdf in batches:
            for component, blob in zip(pdf["component"], pdf["model"], strict=True):
                sides = unpacked(blob).sides
                model = PairModel(specs, sides, cosines, 0)
                for i in range(len(sides) - 1):
                    yield pd.DataFrame({"component": component, "i": sides.ids[i], "j": sides.ids[i + 1 :], "w": model.row(i)[i + 1 :].astype(np.int64)})

    return packed.select("component", "model").mapInPandas(run, "component long, i long, j long, w long")


def decay_weights(infl: np.ndarray, s: Settings) -> np.ndarray:
    """The weights of influence.decay() for one query's members; members outside its canopy have none."""
    inside = np.isfinite(infl)
    n = int(inside.sum())
    pos = np.zeros(len(infl))
    if s.unit == "rank":
        order = np.argsort(np.where(inside, -infl, np.inf), kind="stable")
        pos[order] = np.arange(len(infl))
        p = min(s.p, 5.0 / max(n, 1)) if s.scaled else s.p
    else:
        top, low = infl[inside].max(), infl[inside].min()
        pos[inside] = 0 if top == low else np.floor(100 * (top - infl[inside]) / (top - low))
        p = s.p
    ways = np.ones(len(infl))
    for i in range(1, s.r):
        ways = ways * (pos + i) / i
    return np.where(inside, ways * p**s.r * (1 - p) ** pos, 0.0)


def inverse_weights(infl: np.ndarray) -> np.ndarray:
    inside = np.isfinite(infl)
    top, low = infl[inside].max(), infl[inside].min()
    out = np.zeros(len(infl))
    out[inside] = 1.0 if top == low else 1.0 - (infl[inside] - low) / (top - low)
    return out


def biased(weights: np.ndarray, draw: str) -> Biased:
    if draw == "cdf":
        whole = np.floor(weights * WHOLE + 0.5).astype(np.int64)
        if not whole.any():  # ranks' decay over 10 million mentions
            raise ValueError(f"all weights of {len(whole)} mentions are under half a millionth: draw by an alias table")
        return Biased(whole=whole)
    prob, alias = vose(weights)
    return Biased(prob, alias)


def _chain(whole: Packed, run_id: int, s: Settings, specs, traced: bool = True) -> Chain:
    """The component's chain; of one that is not traced only the state counts."""
    sides = whole.sides
    model = PairModel(specs, sides, s.cosines)
    asked = []
    for query_id, at, places in whole.queries if s.sampler != "uniform" else ():
        infl = np.full(len(sides), -np.inf)
        infl[places] = model.row(at)[places]
        infl[at] = model.own_weight(at)
        asked.append((query_id, at, infl))
    if s.sampler == "auto":
        s = replace(s, sampler="expel" if np.mean([(x[np.isfinite(x)] > 0).mean() for _, _, x in asked]) > 0.5 else "influence_to_query")
    inverse, nodes = s.sampler in ("expel", "expel_both"), []
    if s.sampler == "uniform":  # its proposals ask no influence
        nodes = [Query(query_id, at) for query_id, at, _ in whole.queries]
    for query_id, at, infl in asked:
        nodes.append(Query(query_id, at, None if inverse else biased(decay_weights(infl, s), s.draw), biased(inverse_weights(infl), s.draw) if inverse else None))
    wide = None
    if s.entity_wide:
        by = {x.name: (x.plus, x.minus) for x in specs if x.klass == "entity"}
        off = (0, 0)
        wide = EntityFeatures(np.unique(sides.docs, return_inverse=True)[1], lambda i: model.row(i) > 0, by.get("f15", off), by.get("f16", off), sides.sid, s.matching)
    start = None
    if s.init == "random":
        start = np.array([py_h32(f"init|{s.seed}|{i}") % 8 for i in sides.ids.tolist()])
    elif s.init == "previous":
        start = whole.start
        if start is None:
            raise ValueError("the previous state is needed: pack it")
    single = None if s.init is None else s.init == "single"
    simple = s.sampler == "uniform" and s.accept == "greedy" and s.until is None and s.policy == "round_robin" and wide is None
    if not traced and simple and (found := model.classes(MOST_CLASSES)):
        return ClassChain(sides.ids, model, nodes, s.sampler, s.tau, s.seed, run_id, single=single, start=start, hold=s.hold, of=found[0], between=found[1])
    # Metropolis-Hastings takes no move whose reverse is never proposed: without new entities none could be merged.
    return Chain(sides.ids, model, nodes, s.sampler, s.tau, s.seed, run_id, s.accept, s.temperature, single, start, wide, s.accept == "mh", s.hold)


def run(packed: DataFrame, settings: Settings = Settings(), runs: int = 1, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, first_run: int = 0) -> tuple[DataFrame, DataFrame]:
    """(state, trace) of chains over packed components, each run with its own draws.

    state: (component, run_id, mention_id, entity_id); trace: a row per proposal.  Both are parts of one
    lazily computed table; materialise it if both are used.
    """
    both = chains(packed, settings, runs, specs, first_run)
    return states(both), traces(both)


def states(both: DataFrame) -> DataFrame:
    return both.where("mention_id IS NOT NULL").select("component", "run_id", "mention_id", "entity_id")


def traces(both: DataFrame) -> DataFrame:
    return both.where("step IS NOT NULL").select("component", "run_id", "step", "query_id", "kind", "m", "e_from", "e_to", "delta", "accepted")


def seconds(both: DataFrame) -> DataFrame:
    return both.where("seconds IS NOT NULL").select("component", "run_id", "seconds")


def chains(packed: DataFrame, settings: Settings = Settings(), runs: int = 1, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, first_run: int = 0) -> DataFrame:
    specs, s = tuple(specs), settings
    rows = packed.withColumn("run_id", F.explode(F.sequence(F.lit(first_run), F.lit(first_run + runs - 1))))
    if runs > 1:  # else a component's chain is run where the component lies: it is not sent once more
        rows = rows.repartition(max(packed.sparkSession.sparkContext.defaultParallelism, runs), "component", "run_id")

    def go(batches):
        import time

        for pdf in batches:
            for r in pdf.itertuples(index=False):
                began = time.perf_counter()
                whole = unpacked(r.model)
                chain = _chain(whole, int(r.run_id), s, specs)
                turns = Turns(chain.queries, s.policy, s.samples, s.quantum, {q: len(places) for q, _, places in whole.queries})
                Budget(s.samples, s.until, s.every, s.idle).spend(chain, turns)
                took = time.perf_counter() - began
                yield from _frames(int(r.component), chain, took)

    return rows.mapInPandas(go, RESULT)


def resolved(packed: DataFrame, settings: Settings = Settings(), runs: int = 1, specs: Iterable[features.FeatureSpec] = features.PAIRWISE) -> DataFrame:
    """states(chains()) where nothing else is asked for: no trace leaves the tasks, and simple chains keep none."""
    specs, s = tuple(specs), settings
    rows = packed.select("component", "model", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run_id"))
    rows = rows.repartition(max(4 * packed.sparkSession.sparkContext.defaultParallelism, runs), "component", "run_id")

    def go(batches):
        import pyarrow as pa

        held, size = [], 0

        def out():
            component, run_id, mention_id, entity_id = (np.concatenate(x) for x in zip(*held, strict=True))
            for at in range(0, size, SLICE):
                cols = [x[at : at + SLICE] for x in (component, run_id, mention_id, entity_id)]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in cols], names=["component", "run_id", "mention_id", "entity_id"])

        for batch in batches:
            for component, blob, run_id in zip(*(batch.column(k) for k in ("component", "model", "run_id")), strict=True):
                whole = unpacked(blob.as_py())
                chain = _chain(whole, run_id.as_py(), s, specs, traced=False)
                turns = Turns(chain.queries, s.policy, s.samples, s.quantum, {q: len(places) for q, _, places in whole.queries})
                Budget(s.samples, s.until, s.every, s.idle).spend(chain, turns)
                n = len(chain.ids)
                held.append((np.full(n, component.as_py(), dtype=np.int64), np.full(n, run_id.as_py(), dtype=np.int32), chain.ids, chain.labels()))
                size += n
                if size >= SLICE:
                    yield from out()
                    held, size = [], 0
        if held:
            yield from out()

    return rows.mapInArrow(go, "component long, run_id int, mention_id long, entity_id long")


def _frames(component: int, chain: Chain, took: float):
    """The state in slices, then the seconds and the trace."""
    labels, n, t = chain.labels(), len(chain.ids), len(chain.trace)
    big = lambda x: pd.array(x, dtype="Int64")

    def frame(size: int, **given) -> pd.DataFrame:
        none = {"mention_id": big, "entity_id": big, "step": lambda x: pd.array(x, dtype="Int32"), "query_id": big, "kind": list, "m": big, "e_from": big, "e_to": big, "delta": big, "accepted": lambda x: pd.array(x, dtype="boolean"), "seconds": lambda x: pd.array(x, dtype="Float64")}
        head = {"component": np.full(size, component), "run_id": np.full(size, chain.run, dtype=np.int32)}
        return pd.DataFrame(head | {k: make(given.get(k, [None] * size)) for k, make in none.items()})

    for at in range(0, n, SLICE):
        ids = chain.ids[at : at + SLICE]
        yield frame(len(ids), mention_id=ids, entity_id=labels[at : at + SLICE])
    yield frame(1, seconds=[took])
    if t:
        _, step, query_id, kind, m, e_from, e_to, delta, accepted = zip(*chain.trace, strict=True)
        yield frame(t, step=step, query_id=query_id, kind=kind, m=m, e_from=e_from, e_to=e_to, delta=delta, accepted=accepted)


def answers(state: DataFrame, queries: DataFrame, components: DataFrame | None = None) -> DataFrame:
    """(run_id, query_id, mention_id): the mentions in each query's entity, its own left out.

    A mention in an entity of two queries is an answer of both: they are of one entity then.
    """
    q = queries.select("query_id", F.col("mention_id").alias("own"))
    if components is not None:
        q = q.join(components, "query_id")
    else:
        q = q.withColumn("component", F.col("query_id"))
    at = held(state.withColumnRenamed("mention_id", "own").join(held(q), ["component", "own"]).select("component", "run_id", "query_id", "own", "entity_id"))
    return state.join(at, ["component", "run_id", "entity_id"]).where("mention_id <> own").select("run_id", "query_id", "mention_id")


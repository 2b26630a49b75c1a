"""Exact Jaccard self-join over word shingles by token-combination prefixes, with connected components of the links.

A set of n tokens misses at most slack(n) = n - ceil(t n) of them in any partner of similarity t or more. All tokens stand in one global
order: those in the sampled window of hash space by document frequency class (unique, rare, frequent) and then hash; those outside
the window last, by hash. A prefix is the shortest run of tokens in that order whose signatures can't all be missed: a rare token is a
signature of its own; frequent tokens are dealt by hash to classes, and each pair within a class is a signature, so that a class of c
prefix tokens counts c - 1. Two sets of similarity t or more then share a signature. Unique tokens count, but have no partner: a set with
more unique tokens than its slack has none at all and goes.

Equal sets are one node. Among the nodes that share signatures with others, tokens that one node alone has are counted over whole sets: the overlap of
two nodes is at most either's size less its own such tokens, which bounds the similarity of a pair before it is made. Candidates are verified in
rounds: first each node with one hub; last all pairs that share a signature, meet the bound and are still in different components. Hubs are the
nodes with the least share of lone tokens, so the least edited of a group of near copies: a group of a million costs a million verifications. Nodes with the same hub that are in different components after that are intersected with all of their and the next size
class, in blocks, by products of incidence matrices; only links come out of it. So no link between different components is lost.

Shingles, nodes and signatures are 64-bit hashes, and verification intersects whole ones. Tokens are counted by the top 48 or 40 bits of their hashes: equal
ones could only add candidates.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import DOC_COLUMNS, Bloom, components, cut, lean, mix64, pick, release, shingle_sets, spread_join

#: Production values. WINDOW: share of hash space whose tokens are counted; FREQUENT: document frequency from which pairs are indexed;
#: PART_TOKENS: tokens that one counting task takes.
WIDTH, PERCENT, WINDOW, FREQUENT, PART_TOKENS = 5, 75, 0.4, 16, 1_000_000
_FLUSH = 1_000_000


def _edge(window: float) -> np.uint64:
    """Largest hash in the window; the same for whole hashes and their top 48 bits."""
    return np.uint64(int(window * 2.0**64) | 0xFFFF)


def pack(tokens: np.ndarray, nodes: np.ndarray, width: int = 6) -> bytes:
    """Tokens (their top `width` bytes, by byte position, which compresses what is sorted) and the node of each, as places in a list of nodes."""
    own, place = np.unique(nodes, return_inverse=True)
    size = 2 if len(own) < 1 << 16 else 4
    head = np.array([len(tokens), len(own), width, size], dtype=np.int64)
    return b"".join((head.tobytes(), own.tobytes(), np.ascontiguousarray(tokens.view(np.uint8).reshape(-1, 8)[:, 8 - width :].T).tobytes(), np.ascontiguousarray(place.astype(f"<u{size}").view(np.uint8).reshape(-1, size).T).tobytes()))


def unpack(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, m, width, size = np.frombuffer(blob, dtype=np.int64, count=4).tolist()
    own = np.frombuffer(blob, dtype=np.int64, count=m, offset=32)
    at = 32 + 8 * m
    tokens = np.zeros((n, 8), dtype=np.uint8)
    tokens[:, 8 - width :] = np.frombuffer(blob, dtype=np.uint8, count=n * width, offset=at).reshape(width, n).T
    place = np.ascontiguousarray(np.frombuffer(blob, dtype=np.uint8, offset=at + n * width).reshape(size, n).T).view(f"<u{size}").reshape(-1)
    return tokens.view(np.uint64).reshape(-1), own[place]


def _dealt(tokens: list[np.ndarray], nodes: list[np.ndarray], parts: int, width: int = 6) -> pa.RecordBatch:
    """The tokens dealt to parts by the high bits of their hashes, one packed row for each part that gets any."""
    t, o = np.concatenate(tokens), np.concatenate(nodes)
    order = np.argsort(t, kind="stable")
    t, o = t[order], o[order]
    cuts = np.searchsorted((t >> np.uint64(24)) * np.uint64(parts) >> np.uint64(40), np.arange(parts + 1))
    at = [k for k in range(parts) if cuts[k] < cuts[k + 1]]
    return pa.record_batch([pa.array(at, pa.int32()), pa.array([pack(t[cuts[k] : cuts[k + 1]], o[cuts[k] : cuts[k + 1]], width) for k in at])], names=["part", "blob"])


def _gathered(blobs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct pairs of token and node of a part, in order, and how many nodes have the token."""
    t, o = (np.concatenate(x) for x in zip(*map(unpack, blobs), strict=True))
    order = np.lexsort((o, t))
    t, o = t[order], o[order]
    fresh = np.ones(len(t), dtype=bool)
    fresh[1:] = (t[1:] != t[:-1]) | (o[1:] != o[:-1])
    t, o = t[fresh], o[fresh]
    first = np.ones(len(t), dtype=bool)
    first[1:] = t[1:] != t[:-1]
    runs = np.diff(np.append(np.flatnonzero(first), len(t)))
    return t, o, np.repeat(runs, runs)


def slack(n: int, percent: int) -> int:
    return n - -(-percent * n // 100)


def _levels(n: int, percent: int) -> list[int]:
    """Size classes at which a set of n tokens is indexed: its own, and the next if a partner can be in it."""
    own = n.bit_length() - 1
    return [own, own + 1] if 100 * n >= percent * 2 ** (own + 1) else [own]


def _classes(level: int) -> int:
    return max(1, 2**level // 8)


def _sent(tokens: np.ndarray, percent: int, window: float) -> tuple[int, int]:
    """How many of the sorted tokens lie in the window, and how many are sent to be counted."""
    n = len(tokens)
    inside = int(np.searchsorted(tokens, _edge(window), side="right"))
    need = slack(n, percent) + 1 + max(map(_classes, _levels(n, percent))) if n else 0
    return inside, max(inside, min(n, need))


def set_key(tokens: np.ndarray) -> int:
    """64-bit key of a set."""
    return int(mix64(np.array([mix64(tokens).sum(dtype=np.uint64) + np.uint64(len(tokens))], dtype=np.uint64)).view(np.int64)[0])


def _text_rows(docs: DataFrame) -> DataFrame:
    return pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def profiles(docs: DataFrame, width: int, percent: int, window: float) -> DataFrame:
    """Per row: doc_id, n (set size), node (key of the set), inside (tokens in the window), sent (tokens counted)."""

    def run(batches):
        for b in batches:
            out = [(len(s), set_key(s), *_sent(s, percent, window)) for s in shingle_sets(b.column("text"), width)]
            a = np.array(out, dtype=np.int64).reshape(-1, 4)
            yield pa.record_batch([b.column("doc_id"), *(pa.array(a[:, k]) for k in range(4))], names=["doc_id", "n", "node", "inside", "sent"])

    return _text_rows(docs).mapInArrow(lean(run), "doc_id long, n long, node long, inside long, sent long")


def shared_tokens(docs: DataFrame, parts: int, width: int, percent: int, window: float) -> DataFrame:
    """node, tok, df for each counted token that more than one node has. Tokens go to parts by hash, packed, once per task and node."""

    def send(batches):
        seen: set[int] = set()
        toks: list[np.ndarray] = []
        nodes: list[np.ndarray] = []
        held = 0

        for b in batches:
            for s in shingle_sets(b.column("text"), width):
                if len(s) and (key := set_key(s)) not in seen:
                    seen.add(key)
                    some = s[: _sent(s, percent, window)[1]]
                    toks.append(some)
                    nodes.append(np.full(len(some), key, dtype=np.int64))
                    held += len(some)
                    if held > _FLUSH:
                        yield _dealt(toks, nodes, parts)
                        toks, nodes, held = [], [], 0
        if held:
            yield _dealt(toks, nodes, parts)

    def count(key, pdf):
        import pandas as pd

        t, o, df = _gathered(pdf["blob"])
        keep = df > 1
        out = pd.DataFrame({"node": o[keep], "tok": t[keep].view(np.int64), "df": df[keep].astype(np.int32)})
        del t, o, df
        release()
        return out

    return _text_rows(docs).mapInArrow(lean(send), "part int, blob binary").groupBy("part").applyInPandas(count, "node long, tok long, df int")


def prefix_signatures(n: int, inside: int, toks: np.ndarray, df: np.ndarray, percent: int, window: float, frequent: int) -> np.ndarray:
    """Signatures of one set from its shared counted tokens (uint64) and their document frequencies."""
    order = np.argsort(toks)
    toks, df = toks[order], df[order]
    within = toks <= _edge(window)
    need = slack(n, percent) + 1 - (inside - int(within.sum()))
    if need <= 0:
        return np.zeros(0, np.uint64)
    rare, often, outside = toks[within & (df < frequent)], toks[within & (df >= frequent)], toks[~within]
    found = [mix64(rare[:need])]
    need -= len(found[0])
    for level in _levels(n, percent) if need > 0 else ():
        left, held = need, {}
        of = (mix64(often) % np.uint64(_classes(level))).tolist()
        for t, c in zip(often.tolist(), of, strict=True):
            if left <= 0:
                break
            left -= c in held
            held.setdefault(c, []).append(t)
        for group in held.values():
            g = np.array(group, dtype=np.uint64)
            i, j = np.triu_indices(len(g), 1)
            found.append(mix64(g[i] * np.uint64(0x9FB21C651E98DF25) + mix64(g[j]) + np.uint64(level)))
        if left > 0:
            found.append(mix64(outside))
    return np.unique(np.concatenate(found))


def signatures(shared: DataFrame, nodes: DataFrame, percent: int, window: float, frequent: int) -> DataFrame:
    """sig, node, n. shared: as from shared_tokens; nodes: node, n, inside."""

    def run(batches):
        for b in batches:
            sigs, owner, size = [], [], []
            node, n, inside = (b.column(c).to_numpy() for c in ("node", "n", "inside"))
            for k, (t, d) in enumerate(zip(b.column("toks"), b.column("dfs"), strict=True)):
                s = prefix_signatures(int(n[k]), int(inside[k]), t.values.to_numpy().view(np.uint64), d.values.to_numpy(), percent, window, frequent)
                sigs.append(s)
                owner.append(np.full(len(s), node[k]))
                size.append(np.full(len(s), n[k]))
            if sigs:
                yield pa.record_batch([pa.array(np.concatenate(x).astype(np.uint64).view(np.int64) if x is sigs else np.concatenate(x).astype(np.int64)) for x in (sigs, owner, size)], names=["sig", "node", "n"])

    lists = shared.groupBy("node").agg(F.count("*").alias("m"), F.collect_list("tok").alias("toks"), F.collect_list("df").alias("dfs")).join(nodes, "node")
    some = lists.where(F.col("inside") - F.col("m") <= F.floor(F.col("n") * ((100 - percent) / 100.0)) + 1).select("node", "n", "inside", "toks", "dfs")
    return some.mapInArrow(lean(run), "sig long, node long, n long")


def lone_tokens(sets: DataFrame, parts: int) -> DataFrame:
    """node, lone: how many tokens of a node no other node of sets has."""

    def send(batches):
        toks: list[np.ndarray] = []
        nodes: list[np.ndarray] = []
        held = 0
        for b in batches:
            for node, x in zip(b.column("node").to_pylist(), b.column("toks"), strict=True):
                toks.append(_tokens_of(x.as_py()))
                nodes.append(np.full(len(toks[-1]), node, dtype=np.int64))
                held += len(toks[-1])
                if held > _FLUSH:
                    yield _dealt(toks, nodes, parts, 5)
                    toks, nodes, held = [], [], 0
        if held:
            yield _dealt(toks, nodes, parts, 5)

    def count(key, pdf):
        import pandas as pd

        _, o, df = _gathered(pdf["blob"])
        node, n = np.unique(o[df == 1], return_counts=True)
        del o, df
        release()
        return pd.DataFrame({"node": node, "lone": n})

    return sets.mapInArrow(lean(send), "part int, blob binary").groupBy("part").applyInPandas(count, "node long, lone long").groupBy("node").agg(F.sum("lone").alias("lone"))


def _fits(percent: int):
    """The overlap that the pair's sizes ask for is no more than either side can share with any other node."""
    return ((100 + percent) * F.least("common", "hub_common") >= percent * (F.col("n") + F.col("hub_n"))) & (F.col("node") != F.col("hub"))


def _linked(pdf, percent: int) -> list[tuple[int, int]]:
    """Links between nodes of different labels: of each node one to every label at most. pdf: node, label, side (0 or 1; both if alone), toks."""
    sets = [_tokens_of(x) for x in pdf["toks"]]
    n = np.array([len(x) for x in sets])
    token, at = np.unique(np.concatenate(sets), return_inverse=True)
    often = np.bincount(at) > 1
    place, owner = np.cumsum(often) - 1, np.repeat(np.arange(len(n)), n)
    keep = often[at]
    at, owner = place[at][keep], owner[keep]
    order = np.argsort(at, kind="stable")
    at, owner = at[order], owner[order]
    side, label, node = (pdf[c].to_numpy() for c in ("side", "label", "node"))
    a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
    b = b if len(b) else a
    both = np.zeros((len(a), len(b)), dtype=np.float32)
    step = 4096
    for lo in range(0, int(often.sum()), step):
        i, j = np.searchsorted(at, (lo, lo + step))
        part = np.zeros((len(n), step), dtype=np.float32)
        part[owner[i:j], at[i:j] - lo] = 1
        both += part[a] @ part[b].T
    hit = (100 + percent) * both >= percent * (n[a][:, None] + n[b][None, :])
    hit &= label[a][:, None] != label[b][None, :]
    out = {}
    for i, j in zip(*np.nonzero(hit), strict=True):
        out.setdefault((node[a[i]], label[b[j]]), (int(node[a[i]]), int(node[b[j]])))
    return list(out.values())


def _links_of_hubs(open_nodes: DataFrame, sets: DataFrame, percent: int, block: int = 512) -> DataFrame:
    """a, b: links between nodes of one hub and different labels, by pairs of blocks of nodes. open_nodes: node, label, hub, n.

    Linked sets differ in size by a factor of 100 / percent at most, so nodes are compared within their size class, which is that wide, and with the next one
    only: each node goes to its own class and, for those of the class below, to that."""

    def run(key, pdf):
        import pandas as pd

        found = _linked(pdf, percent)
        release()
        return pd.DataFrame(found, columns=["a", "b"], dtype=np.int64)

    # classes a little wider than the factor, so that rounding can't part a pair by two
    own = F.floor(F.log(F.col("n").cast("double")) / (math.log(100 / percent) * (1 + 1e-9)))
    classed = open_nodes.withColumn("own_class", own).withColumn("class", F.explode(F.array(F.col("own_class"), F.col("own_class") - 1)))
    groups = classed.groupBy("hub", "class").agg(F.count("*").alias("size"), F.min("own_class").alias("low"), F.min("label").alias("lo"), F.max("label").alias("hi"))
    groups = groups.where("lo <> hi AND low = class").select("hub", "class", F.ceil(F.col("size") / block).alias("blocks"))
    placed = classed.join(groups, ["hub", "class"]).withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = placed.select("hub", "class", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "node", "label", (F.col("mine") > F.col("other")).cast("int").alias("side"))
    return dealt.join(sets, "node").groupBy("hub", "class", "i", "j").applyInPandas(run, "a long, b long")


def _tokens_of(x: bytes) -> np.ndarray:
    return np.frombuffer(x, dtype=np.uint64)


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """a, b of the pairs whose sets overlap enough. pairs: a, b. sets: node, toks (packed)."""

    def run(batches):
        for b in batches:
            keep = []
            for x, y in zip(b.column("x"), b.column("y"), strict=True):
                p, q = _tokens_of(x.as_py()), _tokens_of(y.as_py())
                both = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(100 * both >= percent * (len(p) + len(q) - both))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left, right = sets.select(F.col("node").alias("a"), F.col("toks").alias("x")), sets.select(F.col("node").alias("b"), F.col("toks").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(lean(run), "a long, b long")


def _sets_of(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """node, toks (64 bits a token) of the wanted nodes. wanted: doc_id, node; a bounded filter skips most other texts before they are cut in words."""
    bloom = Bloom.of(wanted.select("doc_id"))

    def run(batches):
        held = None
        for b in batches:
            held = held or bloom.test()
            b = b.filter(pa.array(held.may_hold(b.column("doc_id"))))
            keys, packed = [], []
            for s in shingle_sets(b.column("text"), width):
                keys.append(set_key(s))
                packed.append(s.tobytes())
            yield pa.record_batch([pa.array(keys, pa.int64()), pa.array(packed, pa.binary())], names=["node", "toks"])

    return _text_rows(docs).mapInArrow(lean(run), "node long, toks binary").join(wanted.select("node"), "node", "left_semi").dropDuplicates(["node"])


def _still_open(sigs: DataFrame, label: DataFrame) -> DataFrame:
    """sigs with the label of each node, of the signatures that nodes of different labels have."""
    named = sigs.join(label, "node", "left").withColumn("label", F.coalesce("label", "node"))
    mixed = named.groupBy("sig").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("sig")
    return named.join(mixed, "sig", "left_semi")


def near_duplicate_rows(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, window: float = WINDOW, frequent: int = FREQUENT, part_tokens: int = PART_TOKENS) -> DataFrame:
    """Per row of docs: doc_id, n, node, label (key of its component: equal for linked sets; equal sets share a node)."""
    rows = cut(profiles(docs, width, percent, window))
    nodes = cut(rows.where("n > 0").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.max("n").alias("n"), F.max("inside").alias("inside"), F.max("sent").alias("sent")))
    total = nodes.agg(F.coalesce(F.sum("sent"), F.lit(0)).alias("s")).first().s
    shared = shared_tokens(docs, max(1, -(-int(total) // part_tokens)), width, percent, window)
    sigs = signatures(shared, nodes.select("node", "n", "inside"), percent, window, frequent)
    sigs = cut(sigs)
    many = sigs.groupBy("sig").agg(F.count("*").alias("c")).where("c > 1").select("sig")
    met = sigs.join(many, "sig", "left_semi").groupBy("node").agg(F.first("n").alias("n"))
    met = cut(met.join(nodes.select("node", "doc_id"), "node"))
    sets = cut(_sets_of(docs, met.select("doc_id", "node"), width))
    tokens = met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("s")).first().s
    lone = lone_tokens(sets, max(1, -(-int(tokens) // part_tokens)))
    able = met.join(lone, "node", "left").withColumn("common", F.col("n") - F.coalesce("lone", F.lit(0))).where(100 * F.col("common") >= percent * F.col("n")).select("node", "common")
    sigs = cut(sigs.join(many, "sig", "left_semi").join(cut(able), "node"))
    odd = (F.col("n") - F.col("common")) / F.col("n")
    hubs = sigs.groupBy("sig").agg(F.min(F.struct(odd.alias("odd"), "node", "n", "common")).alias("h"), F.count("*").alias("c")).where("c > 1").select("sig", F.col("h.node").alias("hub"), F.col("h.n").alias("hub_n"), F.col("h.common").alias("hub_common"))
    near = sigs.join(hubs, "sig").where(_fits(percent)).groupBy("node", "hub").count()
    best = cut(near.groupBy("node").agg(F.max_by("hub", F.struct("count", "hub")).alias("hub")))
    first = cut(_verified(best.select(F.col("node").alias("a"), F.col("hub").alias("b")), sets, percent))
    own = cut(sigs.join(best, "node", "left").withColumn("own", F.coalesce("hub", "node")).drop("hub"))
    open_ = cut(_still_open(own, components(first)))
    within = cut(_links_of_hubs(open_.select("node", "label", F.col("own").alias("hub"), "n").distinct(), sets, percent))
    links = first.union(within)
    open_ = cut(_still_open(own, components(links)))
    other = open_.select("sig", F.col("node").alias("hub"), F.col("n").alias("hub_n"), F.col("common").alias("hub_common"), F.col("label").alias("hub_label"), F.col("own").alias("hub_own"))
    apart = (F.col("node") < F.col("hub")) & (F.col("label") != F.col("hub_label")) & (F.col("own") != F.col("hub_own"))
    pairs = open_.join(other, "sig").where(_fits(percent) & apart).select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    label = cut(components(links.union(_verified(pairs, sets, percent))))
    # equal sets, and so their rows, may be many
    label = cut(rows.groupBy("node").agg(F.count("*").alias("rows")).join(label, "node"))
    return spread_join(rows, label, "node", "doc_id", "left", "rows").select("doc_id", "n", "node", F.coalesce("label", "node").alias("label"))


def jaccard_components(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_shingles, component_id (least doc_id reachable by links) for every row of docs.

    Null, empty and wordless texts have the empty set, are linked with nothing and are their own component; fewer words than the width are
    one shingle; repeated rows are linked with each other; a null doc_id is larger than any other and stays null where nothing else is in
    the component; an empty table gives no rows; other columns are ignored."""
    rows = cut(near_duplicate_rows(docs, **options))
    least = rows.where("n > 0").groupBy("label").agg(F.min("doc_id").alias("least"), F.count("*").alias("rows"))
    linked = spread_join(rows.where("n > 0"), cut(least), "label", "doc_id", count="rows").select("doc_id", F.col("n").alias("n_shingles"), F.col("least").alias("component_id"))
    return linked.union(rows.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def keep_one_of_each_group(docs: DataFrame, **options) -> DataFrame:
    """One row of each component, that of the least doc_id; rows without words all stay. Columns of documents; edge cases as above.

    Only rows that a bounded filter can't clear of being dropped or repeated are shuffled; the others pass through."""
    width = options.get("width", WIDTH)
    rows = cut(near_duplicate_rows(docs, **options).where("n > 0"))
    kept = rows.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "node")).alias("k")).select("k.doc_id", "k.node")
    repeated = rows.groupBy("doc_id", "node").count().where("count > 1").select("doc_id")
    doubtful = cut(rows.join(kept.select(F.col("doc_id").alias("d"), F.col("node").alias("o")), (F.col("doc_id").eqNullSafe(F.col("d"))) & (F.col("node") == F.col("o")), "left_anti").select("doc_id").union(repeated).where("doc_id is not null").distinct())
    bloom = Bloom.of(doubtful)
    body = pick(docs, *DOC_COLUMNS)

    def clear(batches):
        held = None
        for b in batches:
            held = held or bloom.test()
            yield b.filter(pa.array(~held.may_hold(b.column("doc_id"))))

    def unclear(batches):
        held = None
        for b in batches:
            held = held or bloom.test()
            b = b.filter(pa.array(held.may_hold(b.column("doc_id"))))
            sets = [(len(s), set_key(s)) for s in shingle_sets(b.column("text"), width)]
            a = np.array(sets, dtype=np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(a[:, 0]), pa.array(a[:, 1])], names=[*b.schema.names, "__n", "__node"])

    marked = body.mapInArrow(lean(unclear), T.StructType([*body.schema, T.StructField("__n", T.LongType()), T.StructField("__node", T.LongType())]))
    stay = kept.select(F.col("doc_id").alias("__d"), F.col("node").alias("__o"))
    hit = marked.where("__n = 0").select(*DOC_COLUMNS).union(
        marked.where("__n > 0").join(stay, F.col("doc_id").eqNullSafe(F.col("__d")) & (F.col("__node") == F.col("__o")), "left_semi").withColumn("__r", F.row_number().over(Window.partitionBy("doc_id", "__node").orderBy("__n"))).where("__r = 1").select(*DOC_COLUMNS)
    )
    return body.mapInArrow(lean(clear), body.schema).union(hit)

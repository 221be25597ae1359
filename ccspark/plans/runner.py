"""The phase loop, its methods and baselines.

``connected_components`` is the one entry. Contracting methods give a label map in each
phase; the loop writes the map and the contracted edges, reads two counts from the
writing jobs, and composes the maps backwards at the end. A node is always named by a
vertex of its own component (the owner of its label), so that names of finished and of
unfinished components cannot meet.
"""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ccspark.functions.priority import Priority
from ccspark.operators import absorb as absorbing
from ccspark.operators import contract, finish, labels, stars
from ccspark.operators.edges import endpoints, simplify, symmetrise
from ccspark.plans.metrics import Traffic
from ccspark.plans.store import Scratch

STAT_SCHEMA = "method string, phase int, nodes_in long, edges_in long, labels long, largest_cluster long, jump_steps int, rounds int, records_sent long, bytes_sent long, lookups long, finished_by string, seconds double"
CONTRACTING = ("two_hop", "forest", "rewire_merge")
METHODS = (*CONTRACTING, "star_alternation", "min_hub", "min_spread", "full_cluster", "single_task")


class TooLarge(RuntimeError):
    """A method outgrew the bound on its pairs and was not to contract: the experiment tables mark it ``x``."""


@dataclass
class PhaseStat:
    method: str
    phase: int
    nodes_in: int = 0
    edges_in: int = 0
    labels: int = 0
    largest_cluster: int = 0
    jump_steps: int = 0
    #: Exchanges that sent rows, and what they sent, as counted by Spark; lookups in a map that the tasks hold.
    rounds: int = 0
    records_sent: int = 0
    bytes_sent: int = 0
    lookups: int = 0
    finished_by: str = ""
    seconds: float = 0.0


@dataclass
class Components:
    assignment: DataFrame
    phase_stats: list[PhaseStat]
    scratch: Scratch

    def stats_frame(self) -> DataFrame:
        return self.scratch.spark.createDataFrame([tuple(asdict(s).values()) for s in self.phase_stats], STAT_SCHEMA)

    @property
    def phases(self) -> int:
        return len([s for s in self.phase_stats if s.finished_by != "union_find"])


@dataclass
class Config:
    method: str = "two_hop"
    priority: str = "permute"
    seed: int = 0
    finish_edges: int = 5_000_000
    drop_isolated: bool = True
    absorb: absorbing.Schedule | None = None
    large_moves: bool = False
    lazy: float = 0.0
    reseed: bool = True
    lookup: bool = False
    preforest: bool = False
    salt: int = 0
    strategy: str | None = None
    max_phases: int = 64
    max_pairs: int = 50_000_000
    #: What cluster sets do beyond ``max_pairs``: ``fail``, or ``contract`` the graph that they have become and go on.
    beyond: str = "fail"
    lookup_rows: int = 2_000_000
    details: bool = field(default=False)
    resume: bool = False

    @property
    def prio(self) -> Priority:
        return Priority(self.priority, self.seed)

    def order(self, phase: int) -> int:
        return phase if self.reseed else 0


def _two_hop(edges, cfg: Config, phase, scratch, stat):
    k = cfg.order(phase)
    label = labels.two_hop_min(symmetrise(edges), cfg.prio, k)
    return label.select("v", cfg.prio.owner(F.col("label"), k).alias("node")), edges


def _forest(edges, cfg: Config, phase, scratch, stat):
    k = cfg.order(phase)
    parent = labels.lowest_neighbour(symmetrise(edges), cfg.prio, k)
    rooted = labels.mutual_roots(scratch.write(parent, f"parent-{phase}"), cfg.prio, k)
    if cfg.lookup:
        rooted, n = scratch.counted(rooted, f"rooted-{phase}")
        if n <= cfg.lookup_rows:
            root, seen = scratch.observed(labels.chase_lookup(rooted, cfg.lookup_rows), f"chased-{phase}", hops=F.sum("hops"))
            stat.lookups = seen["hops"] or 0
            return root.select("v", F.col("parent").alias("node")), edges
    root, steps = labels.jump_pointers(rooted, scratch, f"jump-{phase}")
    stat.jump_steps = steps
    return root.withColumnRenamed("parent", "node"), edges


def rewire(edges: DataFrame, prio: Priority, phase: int = 0, scratch: Scratch | None = None) -> DataFrame:
    """Each vertex links its neighbours and itself to the lowest of its closed neighbourhood: canonical edges.

    The hub map is written first: pushed through filters, the inverse order would be copied past the size
    that code generation takes.
    """
    sym, scratch = symmetrise(edges), scratch or Scratch(edges.sparkSession, "rewire")
    low = labels.closed_min(sym, prio, phase).select(F.col("v").alias("src"), prio.owner(F.col("m"), phase).alias("hub"))
    low = scratch.write(low, f"hubs-{phase}")
    own = low.select(F.col("src"), F.col("hub").alias("dst"))
    return simplify(sym.join(low, "src").select(F.col("dst").alias("src"), F.col("hub").alias("dst")).unionByName(own))


def _rewire_merge(edges, cfg: Config, phase, scratch, stat):
    k = cfg.order(phase)
    hubbed = scratch.write(rewire(edges, cfg.prio, k, scratch), f"rewired-{phase}")
    near = labels.closed_min(symmetrise(hubbed), cfg.prio, k)
    return near.select("v", cfg.prio.owner(F.col("m"), k).alias("node")), hubbed


_STEPS = {"two_hop": _two_hop, "forest": _forest, "rewire_merge": _rewire_merge}


def _lazy(label: DataFrame, cfg: Config, phase: int) -> DataFrame:
    """With a fixed chance a vertex keeps its own name as its label, and so becomes its own node."""
    cut = int(cfg.lazy * (1 << 32))
    drawn = F.xxhash64("v", F.lit(cfg.seed), F.lit(phase), F.lit("stay")).bitwiseAND(F.lit(0xFFFFFFFF))
    return label.select("v", F.when(drawn < cut, F.col("v")).otherwise(F.col("node")).alias("node"))


def _done(cfg: Config, scratch: Scratch) -> tuple[list[DataFrame], DataFrame | None]:
    """Maps of the phases that an earlier run of the same folder ended, and the edges after the last of them."""
    maps: list[DataFrame] = []
    last: tuple[int, DataFrame | None] = (0, scratch.read("edges-0") if scratch.has("edges-0") else None)
    for phase in range(cfg.max_phases):
        label, nxt = (f"absorbed-{phase}", f"edges-{phase + 1}a") if scratch.has(f"absorbed-{phase}") else (f"map-{phase}", f"edges-{phase + 1}")
        if not scratch.has(label):
            break
        maps.append(scratch.read(label))
        if scratch.has(nxt):
            last = (phase + 1, scratch.read(nxt))
    return maps[: last[0]], last[1]


def _close(stat: PhaseStat, began: float, traffic: Traffic) -> PhaseStat:
    """The phase's costs: its exchanges and what they sent are read off the finished stages."""
    stat.seconds = time.time() - began
    sent = traffic.take()
    stat.rounds, stat.records_sent, stat.bytes_sent = sent["exchanges"], sent["records"], sent["bytes"]
    return stat


def _contracting(edges: DataFrame, cfg: Config, scratch: Scratch) -> tuple[list[DataFrame], list[PhaseStat]]:
    maps, cur = _done(cfg, scratch) if cfg.resume else ([], None)
    if cur is None:
        cur, m = scratch.counted(simplify(finish.local_forest(edges) if cfg.preforest else edges), "edges-0")
    else:
        m = cur.count()
    stats: list[PhaseStat] = []
    traffic = Traffic(edges.sparkSession)
    alive = None
    if not cfg.drop_isolated:
        alive = maps[-1].select(F.col("node").alias("v")).distinct() if maps else endpoints(cur)
    for phase in range(len(maps), cfg.max_phases):
        if not m:
            break
        began, stat = time.time(), PhaseStat(cfg.method, phase, edges_in=m)
        if m <= cfg.finish_edges:
            label, n = scratch.counted(finish.union_find(cur), f"map-{phase}")
            stat.nodes_in, stat.finished_by = n, "union_find"
            maps.append(label)
            stats.append(_close(stat, began, traffic))
            break
        label, kept = _STEPS[cfg.method](cur, cfg, phase, scratch, stat)
        if cfg.lazy:
            label = _lazy(label, cfg, phase)
        if alive is not None:
            still = alive.join(label.select("v"), "v", "left_anti").select("v", F.col("v").alias("node"))
            label = label.unionByName(still)
        label, stat.nodes_in = scratch.counted(label, f"map-{phase}")
        nxt, m2 = scratch.counted(contract.relabel_edges(kept, label, cfg.strategy, cfg.salt), f"edges-{phase + 1}")
        if cfg.absorb is not None and m2:
            alpha = cfg.absorb.alpha(phase, stat.nodes_in, m)
            label = scratch.write(absorbing.absorb_small(nxt, label, cfg.prio, cfg.order(phase), alpha, cfg.large_moves), f"absorbed-{phase}")
            nxt, m2 = scratch.counted(contract.relabel_edges(kept, label, cfg.strategy, cfg.salt), f"edges-{phase + 1}a")
        if cfg.details:
            row = label.groupBy("node").agg(F.count(F.lit(1)).alias("c")).agg(F.count(F.lit(1)).alias("n"), F.max("c").alias("c")).first()
            stat.labels, stat.largest_cluster = row["n"], row["c"] or 0
        if alive is not None:
            alive = label.select(F.col("node").alias("v")).distinct()
        maps.append(label)
        stats.append(_close(stat, began, traffic))
        if phase:
            scratch.drop(f"edges-{phase - 1}")
        cur, m = nxt, m2
    else:
        if m:
            raise TooLarge(f"{cfg.method} has {m} edges left after {cfg.max_phases} phases")
    return maps, stats


def same_edges(a: DataFrame, b: DataFrame) -> bool:
    """Equal sets of edges (none twice), by count and two order-free checksums, which longs hold at any size."""
    mark = [F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("src", "dst")).alias("h"), F.bit_xor(F.xxhash64("dst", "src")).alias("g")]
    x, y = a.agg(*mark).first(), b.agg(*mark).first()
    return x == y


def _star_alternation(edges, cfg, scratch):
    cur, m = scratch.counted(simplify(edges), "edges-0")
    stats, traffic = [], Traffic(edges.sparkSession)
    for phase in range(cfg.max_phases):
        if not m:
            break
        began, stat = time.time(), PhaseStat("star_alternation", phase, edges_in=m)
        mid, stat.jump_steps, stat.lookups = stars.large_star_run(cur, scratch, same_edges, f"star-{phase}", cfg.lookup, cfg.lookup_rows)
        nxt, m = scratch.counted(stars.small_star(mid), f"edges-{phase + 1}")
        stats.append(_close(stat, began, traffic))
        if same_edges(cur, nxt):
            break
        cur = nxt
    low = symmetrise(cur).groupBy("src").agg(F.min("dst").alias("m"))
    label = low.select(F.col("src").alias("v"), F.least("src", "m").alias("node"))
    return [scratch.write(label, "map")], stats


def _spread(edges, cfg, scratch):
    """Each round a vertex takes the least label of its closed neighbourhood: as many rounds as the diameter."""
    cur, m = scratch.counted(simplify(edges), "edges-0")
    sym = scratch.write(symmetrise(cur), "sym")
    label, n = scratch.counted(endpoints(cur).select("v", F.col("v").alias("node")), "label-0")
    stats, traffic = [], Traffic(edges.sparkSession)
    for phase in range(cfg.max_phases):
        began = time.time()
        heard = sym.join(label.select(F.col("v").alias("dst"), "node"), "dst").groupBy("src").agg(F.min("node").alias("m"))
        step = label.join(heard, label["v"] == heard["src"], "left").select("v", F.least("node", F.coalesce("m", "node")).alias("node"), (F.col("m") < F.col("node")).cast("int").alias("moved"))
        out, seen = scratch.observed(step, f"label-{phase + 1}", moved=F.coalesce(F.sum("moved"), F.lit(0)))
        label = out.select("v", "node")
        scratch.drop(f"label-{phase}")
        stats.append(_close(PhaseStat("min_spread", phase, n, m), began, traffic))
        if not seen["moved"]:
            return [label], stats
    raise TooLarge(f"min_spread still moves after {cfg.max_phases} rounds")


def _contract_pairs(pairs, cfg, phase, scratch):
    """A two-hop phase on the graph of the pairs, which has the components of the edges: its map, the pairs between its nodes and their count."""
    links = pairs.where("v < u").select(F.col("v").alias("src"), F.col("u").alias("dst"))
    label, _ = _two_hop(links, cfg, phase, scratch, None)
    label = scratch.write(label, f"map-{phase}")
    rest = scratch.write(contract.relabel_edges(links, label, cfg.strategy, cfg.salt), f"edges-{phase + 1}")
    return label, *_closed_pairs(rest, scratch, f"pairs-{phase + 1}")


def _closed_pairs(edges, scratch, table: str):
    own = endpoints(edges).select("v", F.col("v").alias("u"))
    return scratch.counted(symmetrise(edges).select(F.col("src").alias("v"), F.col("dst").alias("u")).unionByName(own), table)


def _sent(sizes) -> int:
    """Pairs that sets of these sizes are when each goes to all its members."""
    return sizes.agg(F.sum(F.col("size").cast("decimal(38,0)") * F.col("size"))).first()[0] or 0


def _sent_next(pairs, sizes) -> int:
    """The least that the round after this one sends: a vertex will hold the largest set that any of its members holds now."""
    largest = pairs.join(sizes.select(F.col("v").alias("u"), "size"), "u").groupBy("v").agg(F.max("size").alias("size"))
    return _sent(largest)


def _clusters(edges, cfg, scratch, everyone: bool):
    """Cluster sets kept as (v, member) rows. To the minimum goes the set, to the members the minimum;
    with ``everyone`` the whole set goes to all members.

    The bound is on the pairs that would be sent to all members, else on the pairs held. Beyond it the method fails or,
    with ``beyond="contract"``, merges vertices of a component by a two-hop phase and goes on with the sets
    of what is left: no link is lost. Sets that go to all members are contracted a round earlier where the next
    is sure to be beyond it: what this round sends would only be contracted, and for a star is its square.
    """
    name = "full_cluster" if everyone else "min_hub"
    contracts = cfg.beyond == "contract"
    cur, m = scratch.counted(simplify(edges), "edges-0")
    pairs, n = _closed_pairs(cur, scratch, "pairs-0")
    maps, stats, traffic = [], [], Traffic(edges.sparkSession)
    for phase in range(cfg.max_phases):
        began = time.time()
        low = pairs.groupBy("v").agg(F.min("u").alias("m"), F.count(F.lit(1)).alias("size"))
        cost = _sent(low) if everyone else n
        if contracts and (cost > cfg.max_pairs or everyone and _sent_next(pairs, low) > cfg.max_pairs):
            label, pairs, n = _contract_pairs(pairs, cfg, phase, scratch)
            maps.append(label)
            stats.append(_close(PhaseStat(name, phase, edges_in=m, finished_by="contraction"), began, traffic))
            scratch.drop(f"pairs-{phase}")
            if not n:
                return maps, stats
            continue
        if everyone:
            if cost > cfg.max_pairs and not contracts:
                raise TooLarge(f"full_cluster would send {cost} pairs")
            sent = pairs.select("v", F.col("u").alias("to")).join(pairs, "v").select(F.col("to").alias("v"), "u").distinct()
        else:
            # no member is under the minimum: once these are distinct, so are they with their reverses and the vertices themselves
            down = pairs.join(low.select("v", "m"), "v").where("m < u").select(F.col("m").alias("src"), F.col("u").alias("dst")).distinct()
            sent = symmetrise(down).toDF("v", "u").unionByName(low.select("v", F.col("v").alias("u")))
        nxt, n2 = scratch.counted(sent, f"pairs-{phase + 1}")
        stats.append(_close(PhaseStat(name, phase, edges_in=m), began, traffic))
        if n2 > cfg.max_pairs and not contracts:
            raise TooLarge(f"{name} holds {n2} pairs")
        done = n2 == n and same_edges(pairs.toDF("src", "dst"), nxt.toDF("src", "dst"))
        pairs, n = nxt, n2
        scratch.drop(f"pairs-{phase}")
        if done:
            low = pairs.groupBy("v").agg(F.min("u").alias("node"))
            return [*maps, scratch.write(low, "map")], stats
    raise TooLarge(f"{name} still moves after {cfg.max_phases} rounds")


def _single(edges, cfg, scratch):
    began = time.time()
    cur, m = scratch.counted(simplify(edges), "edges-0")
    label, n = scratch.counted(finish.union_find(cur), "map-0")
    return [label], [PhaseStat("single_task", 0, n, m, finished_by="union_find", seconds=time.time() - began)]


def connected_components(edges: DataFrame, *, vertices: DataFrame | None = None, scratch: Scratch | None = None, **options) -> Components:
    """Assign each vertex the lowest vertex of its component.

    edges: ``src, dst`` in any form (loops, duplicates, either direction; nulls are left out).
    vertices: ``v``, for vertices without edges; they are their own components. options: see :class:`Config`.
    """
    cfg = Config(**options)
    if cfg.method not in METHODS:
        raise ValueError(f"unknown method {cfg.method}; one of {METHODS}")
    if cfg.beyond not in ("fail", "contract"):
        raise ValueError(f"beyond is fail or contract, not {cfg.beyond}")
    scratch = scratch or Scratch(edges.sparkSession, cfg.method)
    if cfg.method in CONTRACTING:
        maps, stats = _contracting(edges, cfg, scratch)
    elif cfg.method in ("min_hub", "full_cluster"):
        maps, stats = _clusters(edges, cfg, scratch, cfg.method == "full_cluster")
    else:
        maps, stats = {"star_alternation": _star_alternation, "min_spread": _spread, "single_task": _single}[cfg.method](edges, cfg, scratch)
    if maps:
        out = contract.canonical_min(contract.compose_back(maps))
    else:
        out = edges.sparkSession.createDataFrame([], "vertex long, component long")
    # a vertex that only loops touch, or that the caller names, is a component of its own
    own = edges.where("src = dst").select(F.col("src").cast("long").alias("vertex"))
    if vertices is not None:
        own = own.unionByName(vertices.select(F.col("v").cast("long").alias("vertex")).where("vertex is not null"))
    lone = own.distinct().join(out.select("vertex"), "vertex", "left_anti").select("vertex", F.col("vertex").alias("component"))
    return Components(scratch.write(out.unionByName(lone), "assignment"), stats, scratch)


def spark_of(df: DataFrame) -> SparkSession:
    return df.sparkSession

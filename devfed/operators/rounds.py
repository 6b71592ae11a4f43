"""Training in synchronous rounds over packed blocks: two tiers, or three with sub-servers.

A round is one job with a constant plan: a map over the blocks that stay where they are, with the
current vectors in its closure. Only members' vectors and row counts come back. Beyond
DRIVER_CLIENTS owners they are merged as a DataFrame and one vector per sub-server comes back.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from collections.abc import Callable, Generator, Iterable, Iterator, Sequence
from dataclasses import dataclass, field, replace
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import DRIVER_CLIENTS, SIMULATED_BYTES, merge_on_driver
from ..sources import tables
from ..sources.checkpoints import materialised
from . import blocks as packed
from . import commcost, localtrain, metrics, splitter, weighting


@dataclass(frozen=True)
class FedConfig:
    """What a run does. The defaults are those of the published experiments; rules are set for each tier."""

    rounds: int = 400
    epochs: int = 10
    lr: float = 0.01
    batch_size: int | None = None
    shuffle: bool = True
    loss: str = "logistic"
    fit_intercept: bool = True
    init: Sequence[float] | None = None
    split: bool = True
    local_mode: str = "params"
    client_rule: str = "proportional"
    subserver_rule: str = "proportional"
    server_rule: str = "proportional"
    sub_share: str = "local"
    sub_rounds: int = 1
    client_rounds: int = 1
    quorum: float | None = None
    eps: float = weighting.EPS
    seed: int = 0
    tol: float | None = None
    strata_fraction: float = 1.0
    flush: int = 50
    history_path: str | None = None
    engine: str = "auto"

    def __post_init__(self) -> None:
        for rule in (self.client_rule, self.subserver_rule, self.server_rule):
            weighting._check(rule)
        if self.local_mode not in ("params", "gradient"):
            raise ValueError("local_mode is 'params' or 'gradient'")
        if self.sub_share not in ("local", "global"):
            raise ValueError("sub_share is 'local' or 'global'")
        if self.loss not in localtrain.SLOPES:
            raise ValueError(f"loss is one of {sorted(localtrain.SLOPES)}")
        if self.quorum is not None and not 0 < self.quorum <= 1:
            raise ValueError("quorum is a share of the clients, above 0")
        if not 0 < self.strata_fraction <= 1:
            raise ValueError("strata_fraction is a share of each cluster's rows, above 0")
        if min(self.rounds, self.epochs, self.sub_rounds, self.client_rounds) < 1:
            raise ValueError("there is at least one round and epoch")
        if self.engine not in ("auto", "driver", "frame"):
            raise ValueError("engine is 'auto', 'driver' or 'frame'")

    def fedavg(self) -> FedConfig:
        """The same run without splitting and with row shares as weights."""
        return replace(self, split=False, client_rule="samples", subserver_rule="samples", server_rule="samples")


@dataclass
class FedResult:
    """weights: the last vector; vectors: of every round, in order."""

    weights: np.ndarray
    vectors: np.ndarray
    first_round: int
    ledger: DataFrame
    models: list[tuple[int, int, int, np.ndarray]] = field(default_factory=list)

    def history(self, spark: SparkSession, method: str = "run") -> DataFrame:
        """(method, round, w), round 1 being the vector after the first round."""
        return spark.createDataFrame([(method, self.first_round + k, [float(x) for x in v]) for k, v in enumerate(self.vectors)], "method string, round long, w array<double>")

    def scored(self, test: DataFrame, features: Sequence[str], method: str = "run", intercept: bool = True) -> DataFrame:
        """Indicators of every round on held-out rows."""
        rounds = np.arange(self.first_round, self.first_round + len(self.vectors))
        return metrics.evaluate_rounds(test, features, rounds, self.vectors, intercept=intercept).select(F.lit(method).alias("method"), "*")


def mark(seed: int, number: int, client: int) -> str:
    """What orders clients by chance in one round."""
    return hashlib.md5(f"{seed}|{number}|{client}".encode()).hexdigest()


def participants(clients: Sequence[int], number: int, quorum: float, seed: int = 0) -> set[int]:
    """The ceil(quorum * clients) clients whose vectors arrive first in a round."""
    last = _last_of(clients, number, quorum, seed)
    return {c for c in clients if (mark(seed, number, c), c) <= last}


def _last_of(clients: Sequence[int], number: int, quorum: float, seed: int) -> tuple[str, int]:
    ordered = sorted((mark(seed, number, c), c) for c in clients)
    return ordered[max(1, math.ceil(quorum * len(ordered))) - 1]


def participants_frame(clients: DataFrame, number: int, quorum: float, seed: int = 0) -> DataFrame:
    """The same for a table of client_id, with the rank in the round."""
    own = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(number)), F.col("client_id").cast("string")))
    return splitter.ranked(clients, own, quorum, key=["client_id"]).select("client_id", F.col("rank").cast("int").alias("rank"))


def _last_of_frame(clients: DataFrame, number: int, quorum: float, seed: int) -> tuple[str, int]:
    """Mark and id of a round's last participant, which tell every task who takes part, however many clients there are."""
    client = participants_frame(clients, number, quorum, seed).agg(F.max_by("client_id", "rank")).first()[0]
    return mark(seed, number, client), client


def train_client(held: dict[int, list], w: np.ndarray, cfg: FedConfig) -> tuple[int, np.ndarray]:
    """One client's rows and new vector, from the one it has received."""
    if not cfg.split:
        held = {0: [b for k in sorted(held) for b in held[k]]}
    clusters = sorted(held)
    rows = np.array([sum(len(y) for _, y in held[c]) for c in clusters], float)
    for step in range(cfg.client_rounds):
        if cfg.local_mode == "gradient":
            slopes = np.stack([sum(localtrain.gradient(x, y, w, cfg.loss) * (len(y) / n) for x, y in held[c]) for c, n in zip(clusters, rows, strict=True)])
            w = w - cfg.lr * weighting.merge_np(slopes, rows, cfg.client_rule, cfg.eps)
        else:
            vectors = np.stack([localtrain.sgd_stream(held[c], w, cfg.epochs, cfg.lr, cfg.batch_size, cfg.seed + step, cfg.loss, cfg.shuffle) for c in clusters])
            w = weighting.merge_np(vectors, rows, cfg.client_rule, cfg.eps)
    return int(rows.sum()), w


def _local(blocks: DataFrame, at: dict[int, np.ndarray], cfg: FedConfig, last: tuple[str, int] | None, number: int = 0) -> DataFrame:
    """(client_id, subserver_id, n_rows, w) after local training from each sub-server's vector; last: the round's last participant."""
    names = ["client_id", "subserver_id", "n_rows", "w"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for client, server, held in packed.clients(batches):
            if last is None or (mark(cfg.seed, number, client), client) <= last:
                n, w = train_client(held, at[server] if server in at else at[-1], cfg)
                yield pa.RecordBatch.from_arrays([pa.array([client], pa.int32()), pa.array([server], pa.int32()), pa.array([n]), pa.array([w.tolist()], pa.list_(pa.float64()))], names)

    return blocks.mapInArrow(run, "client_id int, subserver_id int, n_rows long, w array<double>")


def merge_members(rows: list[tuple[int, int, int, np.ndarray]], cfg: FedConfig, rule: str, three: bool) -> list[tuple[int, float, np.ndarray]]:
    """(sub-server, rows, vector) of each sub-server from (client, sub-server, rows, vector) in order of clients; two tiers have the one sub-server -1."""
    return _merge(np.array([r[1] for r in rows]), np.array([r[2] for r in rows], float), np.stack([r[3] for r in rows]), cfg, rule, three)


def _merge(servers: np.ndarray, counts: np.ndarray, vectors: np.ndarray, cfg: FedConfig, rule: str, three: bool) -> list[tuple[int, float, np.ndarray]]:
    """merge_members of columns: each member's sub-server, rows and vector."""
    total, out = float(counts.sum()) if three and cfg.sub_share == "global" else None, []
    for server in np.unique(servers).tolist():
        own = servers == server
        out.append((server, counts[own].sum(), weighting.merge_np(vectors[own], counts[own], rule, cfg.eps, total)))
    return out


def _servers(members: DataFrame, cfg: FedConfig, rule: str, three: bool, on_driver: bool) -> tuple[list[tuple[int, float, np.ndarray]], list]:
    """merge_members of a DataFrame of members, on the driver or as a DataFrame."""
    if not on_driver:
        # members are read several times, and trained once
        own = materialised(members if three else members.withColumn("subserver_id", F.lit(-1)))
        merged = weighting.merge(own, ["subserver_id"], rule=rule, eps=cfg.eps, share=cfg.sub_share if three else "local").collect()
        return [(r["subserver_id"], float(r["n_rows"]), np.array(r["w"])) for r in merged], []
    rows = sorted(((r["client_id"], r["subserver_id"] if three else -1, r["n_rows"], np.array(r["w"])) for r in members.collect()), key=lambda r: r[0])
    return merge_members(rows, cfg, rule, three), rows


def _centre(servers: list[tuple[int, float, np.ndarray]], cfg: FedConfig, three: bool) -> np.ndarray:
    return weighting.merge_np(np.stack([v for _, _, v in servers]), np.array([n for _, n, _ in servers]), cfg.server_rule, cfg.eps) if three else servers[0][2]


def train(blocks: DataFrame, width: int, cfg: FedConfig, three_tier: bool = False, on_round: Callable[[int, np.ndarray], None] | None = None) -> FedResult:
    """Rounds over blocks (persisted, or read from a table): local training, merging in the client, at sub-servers if there are three tiers, and at the centre. width: parameters with the intercept."""
    spark, w, first = blocks.sparkSession, np.zeros(width) if cfg.init is None else np.array(cfg.init, float), 1
    if cfg.history_path and (found := tables.last_round(spark, cfg.history_path)):
        first, w = found[0] + 1, np.array(found[1])
    known = blocks.select("client_id").distinct()
    # more than the driver merges need not be known by name
    ids = [r[0] for r in known.limit(DRIVER_CLIENTS + 1).collect()] if cfg.quorum or cfg.engine == "auto" else []
    on_driver = cfg.engine == "driver" or (cfg.engine == "auto" and merge_on_driver(len(ids), width))
    vectors, models, pending = [], [], []
    for number in range(first, cfg.rounds + 1):
        last = None
        if cfg.quorum:
            last = _last_of(ids, number, cfg.quorum, cfg.seed) if len(ids) <= DRIVER_CLIENTS else _last_of_frame(known, number, cfg.quorum, cfg.seed)
        at, before = {-1: w}, w
        for _ in range(cfg.sub_rounds if three_tier else 1):
            servers, models = _servers(_local(blocks, at, cfg, last, number), cfg, cfg.subserver_rule if three_tier else cfg.server_rule, three_tier, on_driver)
            # a sub-server without a participant goes on from its last vector
            at = at | {s: v for s, _, v in servers}
        w = _centre(servers, cfg, three_tier)
        vectors.append(w)
        pending.append((number, w.tolist()))
        if on_round:
            on_round(number, w)
        over = number == cfg.rounds or (cfg.tol is not None and np.abs(w - before).max() <= cfg.tol)
        if cfg.history_path and (len(pending) >= cfg.flush or over):
            tables.append_history(spark.createDataFrame(pending, "round int, w array<double>"), cfg.history_path)
            pending = []
        if over:
            break
    done = len(vectors)
    clients = (len(ids) if len(ids) <= DRIVER_CLIENTS else known.count()) or len(models)
    ledger = commcost.ledger(spark, done, clients, width, len(servers) if three_tier and done else None, cfg.sub_rounds, cfg.quorum)
    return FedResult(w, np.array(vectors).reshape(done, width), first, ledger, models)


def fit(df: DataFrame, features: Sequence[str], key: Sequence[str], cfg: FedConfig, three_tier: bool = False, label: str = "label", **split_options) -> FedResult:
    """The whole method on rows with client_id (and subserver_id): split every client, sample its clusters, pack, train.

    cluster_id, if it is there, stands for the splitter's.
    """
    held = prepare(df, features, key, cfg, label, **split_options).persist()
    try:
        return train(held, len(features) + cfg.fit_intercept, cfg, three_tier)
    finally:
        held.unpersist()


def prepare(df: DataFrame, features: Sequence[str], key: Sequence[str], cfg: FedConfig, label: str = "label", **split_options) -> DataFrame:
    """Blocks of the rows that clients train on: split where cfg does, then a stratified sample of each cluster."""
    wanted = [c for c in ("client_id", "subserver_id", "cluster_id") if c in df.columns]
    rows = df.select(*wanted, *key, *(c for c in features if c not in key), label)
    if cfg.split and "cluster_id" not in wanted:
        return splitter.split_blocks(rows, features, key, label, cfg.fit_intercept, fraction=cfg.strata_fraction, seed=cfg.seed, **split_options)
    if cfg.strata_fraction < 1:
        strata = [c for c in ("client_id", "cluster_id") if c in rows.columns]
        rows = splitter.stratified_sample(rows, cfg.strata_fraction, strata, key, cfg.seed)
    return packed.to_blocks(rows, features, label, key, cfg.fit_intercept)


def _places(sizes: dict, tasks: int) -> dict:
    """The task of each owner: the largest first, each to the task with the fewest rows so far."""
    load, out = [(0, t) for t in range(tasks)], {}
    for client in sorted(sizes, key=lambda c: (-sizes[c], c)):
        rows, task = heapq.heappop(load)
        out[client] = task
        heapq.heappush(load, (rows + sizes[client], task))
    return out


def _course(cfg: FedConfig, width: int, ids: Sequence[int], three: bool) -> Generator[tuple[dict, tuple | None, int], tuple, list[tuple[np.ndarray, int]]]:
    """A run's rounds without its rows: asks for training (from which vectors, the last participant, the round), is sent all members' sub-servers, rows and vectors, returns (vector, sub-servers) of each round."""
    w, out = np.zeros(width), []
    for number in range(1, cfg.rounds + 1):
        last, at = _last_of(ids, number, cfg.quorum, cfg.seed) if cfg.quorum else None, {-1: w}
        for _ in range(cfg.sub_rounds if three else 1):
            members = yield at, last, number
            servers = _merge(*members, cfg, cfg.subserver_rule if three else cfg.server_rule, three)
            at = at | {s: v for s, _, v in servers}
        w = _centre(servers, cfg, three)
        out.append((w, len(servers)))
    return out


@dataclass(frozen=True)
class _Deal:
    """Which task trains which share of the runs on which owner's rows: an owner of more rows than an even part lies with several tasks, each of which trains some of the runs on all of them."""

    ids: list[int]
    servers: np.ndarray
    counts: np.ndarray
    shares: dict[int, int]
    places: dict[tuple[int, int], int]

    @classmethod
    def of(cls, owners: dict[int, tuple[int, int]], tasks: int, runs: int) -> _Deal:
        """owners: (sub-server, rows) by owner."""
        ids, every = sorted(owners), sum(n for _, n in owners.values())
        shares = {c: max(1, min(tasks, runs, math.ceil(owners[c][1] * tasks / max(1, every)))) for c in ids}
        places = _places({(c, s): owners[c][1] / shares[c] for c in ids for s in range(shares[c])}, tasks)
        return cls(ids, np.array([owners[c][0] for c in ids]), np.array([owners[c][1] for c in ids], float), shares, places)

    def held(self) -> list[tuple[int, int]]:
        """(owner, task) wherever an owner's rows lie."""
        return sorted({(c, t) for (c, _), t in self.places.items()})

    def parts(self, task: int) -> list[tuple[int, int, list[int]]]:
        """A task's owners by (shares, share), in an order that all tasks know."""
        out = {}
        for (c, s), t in sorted(self.places.items()):
            if t == task:
                out.setdefault((self.shares[c], s), []).append(c)
        return [(k, s, own) for (k, s), own in sorted(out.items())]


def _jobs(asked: dict[str, tuple]) -> dict[str, tuple]:
    """What each run asks of its clients; runs that start a round alike and descend and merge alike in the client ask the same, which is trained once."""
    out = {}
    for name, (cfg, at, _, _) in asked.items():
        if cfg.batch_size is None and cfg.local_mode == "params" and cfg.client_rounds == 1:
            # one cluster is merged alike by every rule
            merging = (cfg.client_rule, cfg.eps) if cfg.split else ()
            out[name] = (cfg.split, cfg.epochs, cfg.lr, cfg.loss), tuple((s, at[s].tobytes()) for s in sorted(at)), merging
        else:
            out[name] = (), name, ()
    return out


class _Owners:
    """A task's owners, which train for many runs at once: runs that descend alike share the products of each stack of clusters."""

    def __init__(self, rows: Iterable[Row], deal: _Deal):
        self.owners, task = {}, None
        for client, own in groupby(sorted(rows, key=lambda r: (r["client_id"], r["cluster_id"], r["block"])), key=lambda r: r["client_id"]):
            own = list(own)
            x, y = (np.concatenate(p) for p in zip(*(packed.matrices(r["x"], r["y"]) for r in own), strict=True))
            ends, task = np.cumsum([r["n"] for r in own]), own[0]["__task"]
            self.owners[client] = own[-1]["subserver_id"], x, y, [(r["cluster_id"], int(e - r["n"]), int(e)) for r, e in zip(own, ends, strict=True)]
        self.parts = deal.parts(task) if self.owners else []

    def _held(self, client: int) -> dict[int, list]:
        """An owner's blocks by cluster, as views of its rows."""
        _, x, y, parts = self.owners[client]
        out = {}
        for cluster, a, b in parts:
            out.setdefault(cluster, []).append((x[a:b], y[a:b]))
        return out

    def _form(self, split: bool, own: list[int]) -> tuple:
        """Clusters of owners in stacks, their rows, sub-servers, and where each owner's begin."""
        units = [(c, blocks) for c in own for blocks in (self._held(c).values() if split else [[self.owners[c][1:3]]])]
        first = [*(i for i, u in enumerate(units) if i == 0 or u[0] != units[i - 1][0]), len(units)]
        return localtrain.stacks([u[1] for u in units]), np.array([sum(len(y) for _, y in u[1]) for u in units], float), [self.owners[u[0]][0] for u in units], first

    def _train(self, own: list[int], asked: dict[tuple, tuple]) -> np.ndarray:
        """The vectors of owners for some jobs: (jobs, owners, width)."""
        found, alike = {}, {}
        for job, (cfg, at, *_) in asked.items():
            if job[0]:
                alike.setdefault(job[0], {}).setdefault(job[1], []).append(job)
            else:
                found[job] = np.stack([train_client(self._held(c), at.get(self.owners[c][0], at[-1]), cfg)[1] for c in own])
        forms = {split: self._form(split, own) for split in {k[0] for k in alike}}
        for (split, epochs, lr, loss), starts in alike.items():
            stacked, sizes, servers, first = forms[split]
            ats = [asked[same[0]][1] for same in starts.values()]
            begun = np.stack([[at.get(s, at[-1]) for s in servers] for at in ats])
            for same, vectors in zip(starts.values(), localtrain.sgd_stacked(stacked, begun, epochs, lr, loss), strict=True):
                for job in same:
                    cfg = asked[job][0]
                    found[job] = np.stack([weighting.merge_np(vectors[a:b], sizes[a:b], cfg.client_rule, cfg.eps) for a, b in zip(first, first[1:], strict=False)]) if split else vectors
        return np.stack([found[job] for job in asked])

    def train(self, asked: dict[tuple, tuple]) -> list[tuple[list[int], list[int], np.ndarray]]:
        """(places of jobs, owners, their vectors) of this task's shares."""
        # jobs of one kind and start lie in one share, as they descend once
        starts = {start: k for k, start in enumerate(dict.fromkeys(job[:2] for job in asked))}
        out = []
        for shares, share, own in self.parts:
            some = [i for i, job in enumerate(asked) if starts[job[:2]] % shares == share]
            if some:
                every = list(asked.items())
                out.append((some, own, self._train(own, dict(every[i] for i in some))))
        return out


def simulate(blocks: DataFrame, width: int, configs: dict[str, FedConfig], three_tier: bool = False) -> dict[str, FedResult]:
    """``train`` for many configurations side by side: each round of all of them is one job.

    Owners are dealt to as many tasks as there are cores, about equal in work, and kept there as matrices; only members' vectors
    come back, which the driver merges. For at most SIMULATED_BYTES of rows a task; beyond, and for runs with a history, a tolerance or
    a first vector, each configuration is trained in rounds over the blocks.
    """
    spark, plain = blocks.sparkSession, all(c.history_path is None and c.tol is None and c.init is None for c in configs.values())
    found = blocks.groupBy("client_id").agg(F.max_by("subserver_id", F.struct("cluster_id", "block")).alias("server"), F.sum("n").alias("n")).limit(DRIVER_CLIENTS + 1).collect()
    owners, tasks = {r["client_id"]: (r["server"], r["n"]) for r in found}, max(1, spark.sparkContext.defaultParallelism)
    deal = _Deal.of(owners, tasks, len(configs))
    held = np.bincount([t for _, t in deal.held()], [owners[c][1] for c, _ in deal.held()], tasks)
    if not plain or len(owners) > DRIVER_CLIENTS or held.max() * (width + 1) * 8 > SIMULATED_BYTES:
        return {name: train(blocks, width, cfg, three_tier) for name, cfg in configs.items()}
    done = {name: [] for name in configs}
    if owners:
        place = spark.createDataFrame(deal.held(), "client_id int, __task int")
        dealt = blocks.join(F.broadcast(place), "client_id").repartitionById(tasks, F.col("__task")).select(*packed.NAMES, "__task")
        kept = dealt.rdd.mapPartitions(lambda rows: [_Owners(rows, deal)]).persist(StorageLevel.MEMORY_AND_DISK)
        where, servers = {c: i for i, c in enumerate(deal.ids)}, deal.servers if three_tier else np.full(len(owners), -1)
        try:
            courses = {name: _course(cfg, width, deal.ids, three_tier) for name, cfg in configs.items()}
            asked = {name: (configs[name], *next(course)) for name, course in courses.items()}
            while asked:
                now, asked, jobs = asked, {}, _jobs(asked)
                # equal jobs are asked once
                told = {job: now[name] for name, job in jobs.items()}
                vectors = np.empty((len(told), len(owners), width))
                for some, own, values in kept.map(lambda own, told=told: own.train(told)).flatMap(lambda found: found).collect():
                    vectors[np.ix_(some, [where[c] for c in own])] = values
                place = {job: k for k, job in enumerate(told)}
                for name, (cfg, _, last, number) in now.items():
                    some = slice(None) if last is None else np.array([(mark(cfg.seed, number, c), c) <= last for c in deal.ids])
                    try:
                        asked[name] = (cfg, *courses[name].send((servers[some], deal.counts[some], vectors[place[jobs[name]]][some])))
                    except StopIteration as over:
                        done[name] = over.value
        finally:
            kept.unpersist()
    out = {}
    for name, cfg in configs.items():
        vectors = np.array([w for w, _ in done[name]]).reshape(len(done[name]), width)
        ledger = commcost.ledger(spark, len(vectors), len(owners), width, done[name][-1][1] if three_tier and done[name] else None, cfg.sub_rounds, cfg.quorum)
        out[name] = FedResult(vectors[-1] if len(vectors) else np.zeros(width), vectors, 1, ledger)
    return out

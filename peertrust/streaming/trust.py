"""Ledgers as streams: batches, stateful pair nets, and trust kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from peertrust import metrics, packed, walks
from peertrust.estimate import estimate
from peertrust.functions.rng import RNG_SEED
from peertrust.graph import edges_from_net, net_by_pair
from peertrust.incremental import LOCAL_VISITS, RefreshPolicy, apply_changes, drop_seed_check, local_update
from peertrust.power import ROUNDS, power_iteration, solve
from peertrust.schemas import PROPS, WALK
from peertrust.sources.files import write_in_order
from peertrust.sources.tables import DOWN_KINDS, UP_KINDS, cut
from peertrust.streaming.operators import drain
from peertrust.walks import Adjacency, run_walks, simulate_walks, step_cap

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, sf_dir: str, pattern: str = "events.parquet", per_trigger: int = 1) -> DataFrame:
    """``events`` as a stream, with an event time that takes watermarks; a micro-batch
    has ``per_trigger`` files."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def ledger_files(events: DataFrame, path: str, by: str = "time", parts: int = 6, n_events: int | None = None) -> DataFrame:
    """``events`` as a folder that a stream reads a micro-batch at a time: a file a day, or
    ``parts`` files of equal volume, in the order of time.  Returns them with ``batch``."""
    rows = events.withColumn("at", F.col("ts").cast("timestamp"))
    if by == "time":
        first = rows.agg(F.min(F.to_date("at")).alias("first"))
        batch = rows.join(F.broadcast(first), how="cross").withColumn("batch", F.date_diff(F.to_date("at"), F.col("first")).cast("long")).drop("first")
    else:
        n = rows.count() if n_events is None else n_events
        batch = batches(rows.withColumn("id", F.col("event_id")).withColumn("ts", F.col("at")), "volume", max(1, -(-n // parts))).drop("id").withColumn("ts", F.col("at").cast("timestamp_ntz"))
    batch = batch.drop("at")
    write_in_order(batch, "batch", path)
    return batch


def transfers_of(events: DataFrame, n_peers: int) -> DataFrame:
    """Transfers of a (streamed) batch; the number of peers is known beforehand."""
    cents = F.round(F.col("value") * 100).cast("long")
    rows = events.select(
        F.col("event_id").alias("id"), F.col("user_id").alias("p"), F.pmod(F.col("user_id") + 1 + F.from_json("props", PROPS)["k"], F.lit(n_peers)).alias("q"),
        F.when(F.col("event_type").isin(*UP_KINDS), cents).otherwise(0).alias("up"), F.when(F.col("event_type").isin(*DOWN_KINDS), cents).otherwise(0).alias("down"),
        F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("kind"),
    )
    return rows.filter("p <> q")


def batches(transfers: DataFrame, by: str = "time", size: int = 1_000) -> DataFrame:
    """``batch`` of every transfer: its day, or its place in the ledger over ``size``."""
    if by == "time":
        first = transfers.agg(F.min(F.to_date("ts")).alias("first"))
        return transfers.join(F.broadcast(first), how="cross").withColumn("batch", F.date_diff(F.to_date("ts"), F.col("first")).cast("long")).drop("first")
    # places are counted within days and offset by the days before: no single task numbers all rows
    day = F.to_date("ts")
    rows = transfers.withColumn("_day", day)
    sizes = rows.groupBy("_day").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_before", F.sum("_n").over(Window.orderBy("_day")) - F.col("_n")).drop("_n")
    local = F.row_number().over(Window.partitionBy("_day").orderBy("ts", "id")) - 1
    return rows.withColumn("_r", local).join(F.broadcast(before), "_day").withColumn("batch", F.floor((F.col("_before") + F.col("_r")) / F.lit(size))).drop("_day", "_r", "_before")


_NET = "a long, b long, net long"
_COLUMNS = ["walk_id", "seed", "gen", "step", "node"]
_FOLLOWED = f"i int, {WALK}, l2 double, linf double"


def known(blocks: DataFrame, before: bool = False) -> DataFrame:
    """The edges of blocks; they can be read again and again, as they are only unpacked."""
    edges = packed.edges_of(blocks, before)
    edges._peertrust_cut, edges._peertrust_blocks, edges._peertrust_before = True, blocks, before
    return edges


def _first_walks(graph: Adjacency, seed: int, n_walks: int, alpha: float) -> pd.DataFrame:
    first = pd.DataFrame({"walk_id": np.arange(n_walks), "seed": seed, "gen": 0, "step": 0, "node": seed})
    rest = run_walks(graph, first, np.full(n_walks, alpha), RNG_SEED, step_cap(alpha))
    return pd.concat([first, rest], ignore_index=True).astype({"gen": "int32", "step": "int32"})


def _distances(visits: pd.DataFrame, src: np.ndarray, dst: np.ndarray, w: np.ndarray, seed: int, alpha: float, exact: tuple | None = None) -> dict[str, float]:
    """Distance of the walks' scores to power iteration."""
    node, score = exact or _exact(src, dst, w, seed, alpha)
    mine = visits["node"].value_counts(normalize=True).reindex(node).fillna(0).to_numpy()
    return {"l2": float(np.sqrt(((mine - score) ** 2).sum())), "linf": float(np.abs(mine - score).max())}


def _exact(src: np.ndarray, dst: np.ndarray, w: np.ndarray, seed: int, alpha: float) -> tuple[np.ndarray, np.ndarray]:
    node = np.unique(np.concatenate([np.unique(src), np.unique(dst), [seed]]))
    return node, solve(src, dst, w, node, seed, alpha, "seed", ROUNDS)[0]


def _follow(plans: list[dict], a: np.ndarray, b: np.ndarray, was: np.ndarray, net: np.ndarray) -> pd.DataFrame:
    """Walks of each plan after the last change of the pairs, and a row with their error
    if it is asked for; all plans share the adjacency and the exact scores."""
    new, out, exact = packed.directed(a, b, net), [], {}
    graph = Adjacency(*new) if any(p["gen"] is not None for p in plans) else None
    for i, p in enumerate(plans):
        visits = p["walks"]
        if visits is None:
            visits = _first_walks(graph, p["seed"], p["n_walks"], p["alpha"])
        elif p["gen"] is not None:
            seen = np.unique(visits["node"])  # no other law can change a walk
            near = np.isin(a, seen) | np.isin(b, seen)
            laws = [pd.DataFrame(dict(zip(("src", "dst", "w"), e, strict=True))).astype("int64") for e in (packed.directed(a[near], b[near], x[near]) for x in (was, net))]
            visits = local_update(visits, *(e[e["src"].isin(seen)].reset_index(drop=True) for e in laws), p["gen"], p["alpha"], p["policy"], graph=graph)
        if p["gen"] is not None:
            out.append(visits.assign(i=i, l2=np.nan, linf=np.nan))
        if p["measured"]:
            key = p["seed"], p["alpha"]
            exact[key] = exact.get(key) or _exact(*new, *key)
            out.append(pd.DataFrame({"i": i, **dict.fromkeys(_COLUMNS, 0), **_distances(visits, *new, *key, exact[key])}, index=[0]))
    kinds = {"i": "int32", "walk_id": "int64", "seed": "int64", "gen": "int32", "step": "int32", "node": "int64", "l2": "float64", "linf": "float64"}
    return pd.concat(out, ignore_index=True)[list(kinds)].astype(kinds)


class TrustStore:
    """Pair nets, walks and scores, moved on a batch at a time.

    While pairs and visits are few (counted first, ``LOCAL_PAIRS`` and ``LOCAL_VISITS``),
    they are arrays on the driver and a batch costs one aggregation of its own
    transfers; beyond, pairs are blocks of arrays in the shared folder, which one task of
    an executor gathers for all stores of a stream while it can hold them
    (``BROADCAST_EDGES``), and joins follow the walks beyond that.  All give the same rows.

    ``refresh`` says when walks are drawn anew instead of updated.  If it has a largest
    error, the error of the updated scores is measured after each batch, against power
    iteration on the graph as it is.  ``max_pairs`` bounds the work of an update: changes
    of more pairs wait for the next ones, in hashed order, so load is even and walks
    always belong to one graph (that of the pairs taken in so far)."""

    #: Less than ``LOCAL_EDGES``: an update groups and sorts them, in each store of a stream.
    LOCAL_PAIRS = 150_000

    def __init__(self, spark: SparkSession, seed: int, n_walks: int = 300, alpha: float = 0.3, policy: str = "coupling", refresh: RefreshPolicy | None = None, max_pairs: int | None = None, seed_must_stay: bool = False):
        self.max_pairs, self.waiting, self.seed_must_stay = max_pairs, None, seed_must_stay
        self.spark, self.seed, self.n_walks, self.alpha, self.policy = spark, seed, n_walks, alpha, policy
        self.refresh = refresh or RefreshPolicy()
        self.batch, self.rebuilds, self.errors, self.hops = 0, 0, [], 0
        self._net: pd.DataFrame | DataFrame = pd.DataFrame({c: pd.Series(dtype="int64") for c in ("a", "b", "net")})
        self._walks: pd.DataFrame | DataFrame | None = None
        # of a store of tables
        self._blocks: DataFrame | None = None
        self._edges: DataFrame | None = None
        self._pairs, self._error = 0, None
        self._exact: DataFrame | None = None  # scores of a graph that no one task gathers

    @property
    def local(self) -> bool:
        return self._blocks is None

    def _frame(self, x: pd.DataFrame | DataFrame, schema) -> DataFrame:
        return self.spark.createDataFrame(pa.Table.from_pandas(x, preserve_index=False), schema) if isinstance(x, pd.DataFrame) else x

    @property
    def edges(self) -> DataFrame:
        return self._edges if self._edges is not None else edges_from_net(self._frame(self._net, _NET))

    @property
    def walks(self) -> DataFrame | None:
        return None if self._walks is None else self._frame(self._walks, WALK)

    def update(self, transfers: DataFrame, like: TrustStore | None = None) -> None:
        """``like``: a store that has taken in the same transfers so far, these included;
        its tables are this store's, too."""
        if self._take(transfers, like):
            self._move([self])

    @staticmethod
    def update_together(stores: list[TrustStore], transfers: DataFrame) -> None:
        """``update`` of stores that have taken in the same transfers so far.  Those that
        share their tables have their walks moved by one task."""
        if all(s.max_pairs is None for s in stores):
            nets = cut(packed.packed(net_by_pair(transfers)))
        else:
            transfers, nets = cut(transfers), None
        moving = [s for s in stores if s._take(transfers, stores[0] if s is not stores[0] else None, nets)]
        shared = [s for s in moving if s._blocks is stores[0]._blocks]
        if shared:
            TrustStore._move(shared)
        for s in moving:
            if s not in shared:
                TrustStore._move([s])

    def _take(self, transfers: DataFrame, like: TrustStore | None, nets: DataFrame | None = None) -> bool:
        """Takes in transfers (``nets``: their nets as blocks); whether the walks are still
        to follow."""
        shared = like is not None and not like.local and self.max_pairs is None and like.max_pairs is None
        if shared:
            self.batch, self._blocks, self._pairs, self._edges = self.batch + 1, like._blocks, like._pairs, like._edges
            self._net, self._error, self._exact = None, None, None
            return True
        delta = net_by_pair(transfers) if nets is None else None
        if self.waiting is not None:
            delta = self.waiting.union(delta).groupBy("a", "b").agg(F.sum("net").alias("net"))
        if self.max_pairs is not None:
            delta = cut(delta)
            taken = cut(delta.orderBy(F.xxhash64("a", "b"), "a", "b").limit(self.max_pairs))
            self.waiting = cut(delta.join(taken.select("a", "b"), ["a", "b"], "left_anti"))
            delta = taken
        self.batch += 1
        fresh = cut(packed.packed(delta)) if nets is None else nets
        n = packed.pairs(fresh)
        if self.local:
            if len(self._net) + n <= self.LOCAL_PAIRS and (self._walks is None or len(self._walks) <= LOCAL_VISITS):
                found = [x[1:] for x in packed.read(fresh.toArrow().to_batches())]
                self._update_local(pd.DataFrame({c: np.concatenate([x[i] for x in found]).astype(np.int64) if found else np.empty(0, np.int64) for i, c in ((0, "a"), (1, "b"), (3, "net"))}))
                return False
            self._pairs = len(self._net)
            self._blocks = packed.merged(*(packed.packed(self._frame(x, _NET)) for x in (self._net, self._net.iloc[:0])), self._pairs)
        self._blocks = packed.merged(self._blocks, fresh, self._pairs + n)
        self._pairs, self._edges = packed.pairs(self._blocks), known(self._blocks)
        self._net, self._error, self._exact = None, None, None
        return True

    @staticmethod
    def _move(stores: list[TrustStore]) -> None:
        """The walks of stores of the same tables follow the last change."""
        blocks = stores[0]._blocks
        for s in stores:
            if s.seed_must_stay:
                drop_seed_check(s._edges, s.seed)
        few = [s for s in stores if stores[0]._pairs <= walks.BROADCAST_EDGES and s.n_walks <= walks.GATHERED_WALKS and (s._walks is None or isinstance(s._walks, pd.DataFrame))]
        if few:
            plans = [{**s._plan(), "walks": None if s._anew() else s._walks, "gen": s.batch, "measured": s.refresh.max_error is not None} for s in few]
            rows = packed.gathered(blocks, lambda *pairs: _follow(plans, *pairs), _FOLLOWED)
            for i, s in enumerate(few):
                s._moved(rows[rows["i"] == i])
        exact: dict[tuple, DataFrame] = {}
        for s in stores:
            if s not in few:
                s._exact = exact.get((s.seed, s.alpha), s._exact)
                s._move_tables()
                exact[s.seed, s.alpha] = s._exact

    def _anew(self) -> bool:
        return self._walks is None or self.refresh.due(self.batch, self._last_error())

    def _plan(self) -> dict:
        return {"seed": self.seed, "n_walks": self.n_walks, "alpha": self.alpha, "policy": self.policy}

    def _moved(self, rows: pd.DataFrame) -> None:
        anew = self._anew()
        mine = rows[rows["l2"].isna()][_COLUMNS].reset_index(drop=True).astype({"gen": "int32", "step": "int32"})
        self._walks, self.rebuilds = mine, self.rebuilds + anew
        self.hops = int(((mine["step"] > 0) if anew else (mine["gen"] == self.batch)).sum())
        if self.refresh.max_error is not None:
            self._error = rows.loc[rows["l2"].notna(), ["l2", "linf"]].iloc[0].to_dict()
            self.errors.append(self._error["l2"])

    def _move_tables(self) -> None:
        self._walks = None if self._walks is None else cut(self.walks)
        if self._anew():
            self._walks, self.rebuilds = cut(simulate_walks(self._edges, self.seed, self.n_walks, self.alpha)), self.rebuilds + 1
            self.hops = self._walks.filter("step > 0").count()
        else:
            old = known(self._blocks, before=True)
            self._walks = cut(apply_changes(self._walks, old, self._edges, self.batch, self.alpha, self.policy, strategy="joins"))
            self.hops = self._walks.filter(F.col("gen") == self.batch).count()
        if self.refresh.max_error is not None:
            self.errors.append(self.measured_error()["l2"])

    def _last_error(self) -> float | None:
        return self.errors[-1] if self.errors else None

    @staticmethod
    def _arrays(net: pd.DataFrame) -> pd.DataFrame:
        net = net[net["net"] != 0]
        giver = net["net"].to_numpy() > 0
        a, b = net["a"].to_numpy(), net["b"].to_numpy()
        return pd.DataFrame({"src": np.where(giver, b, a), "dst": np.where(giver, a, b), "w": np.abs(net["net"].to_numpy())})

    def _update_local(self, delta: pd.DataFrame) -> None:
        old = self._arrays(self._net)
        self._net = pd.concat([self._net, delta]).groupby(["a", "b"], as_index=False)["net"].sum()
        new = self._arrays(self._net)
        if self.seed_must_stay and not ((new["src"] == self.seed) | (new["dst"] == self.seed)).any():
            raise ValueError(f"seed {self.seed} is no longer in the graph")
        if self._walks is None or self.refresh.due(self.batch, self._last_error()):
            self._walks = _first_walks(Adjacency(*(new[c].to_numpy() for c in ("src", "dst", "w"))), self.seed, self.n_walks, self.alpha)
            self.rebuilds, self.hops = self.rebuilds + 1, int((self._walks["step"] > 0).sum())
        else:
            self._walks = local_update(self._walks, old, new, self.batch, self.alpha, self.policy)
            self.hops = int((self._walks["gen"] == self.batch).sum())
        if self.refresh.max_error is not None:
            self.errors.append(self.measured_error()["l2"])

    def measured_error(self) -> dict[str, float]:
        """Distance of the walks' scores to power iteration."""
        if not self.local:
            if self._error is None and isinstance(self._walks, pd.DataFrame):
                plans = [{**self._plan(), "walks": self._walks, "gen": None, "measured": True}]
                rows = packed.gathered(self._blocks, lambda *pairs: _follow(plans, *pairs), _FOLLOWED)
                self._error = rows.loc[rows["l2"].notna(), ["l2", "linf"]].iloc[0].to_dict()
            if self._error is None:
                if self._exact is None:
                    self._exact = cut(power_iteration(self._edges, self.seed, self.alpha))
                row = metrics.differences(self.scores(), self._exact).first()
                self._error = {"l2": row.l2, "linf": row.linf}
            return self._error
        edges = self._arrays(self._net)
        return _distances(self._walks, *(edges[c].to_numpy() for c in ("src", "dst", "w")), self.seed, self.alpha)

    def scores(self) -> DataFrame:
        return estimate(self.walks)


def stream_trust(events: DataFrame, n_peers: int, store: TrustStore | list[TrustStore], checkpoint: str, query_name: str = "trust"):
    """A running query that feeds each micro-batch to the store (or to several)."""
    stores = store if isinstance(store, list) else [store]

    def feed(batch: DataFrame, _: int) -> None:
        TrustStore.update_together(stores, transfers_of(batch, n_peers))
        # what the batch is done with goes now, with its checkpoints; the driver's heap does
        # not fill up with it first
        batch.sparkSession._jvm.System.gc()

    return events.writeStream.queryName(query_name).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(feed).start()


def pair_nets_stateful(transfers: DataFrame) -> DataFrame:
    """``a, b, net, flipped`` after each batch of a pair, kept in the state of the
    stream: a pair's state is one number."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        net = state.get[0] if state.exists else 0
        old = net
        for part in parts:
            net += int(part["g"].sum())
        state.update((net,))
        yield pd.DataFrame({"a": [key[0]], "b": [key[1]], "net": [net], "flipped": [old * net < 0]})

    given = F.when(F.col("p") < F.col("q"), F.col("up") - F.col("down")).otherwise(F.col("down") - F.col("up"))
    rows = transfers.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), given.alias("g"))
    return rows.groupBy("a", "b").applyInPandasWithState(step, "a long, b long, net long, flipped boolean", "net long", "append", "NoTimeout")


def pair_nets_by_batch(transfers: DataFrame) -> DataFrame:
    """``a, b, net, flipped`` after each micro-batch of a pair, for all that the stream has
    now.  The state is that of a streaming sum, so no pair is a call of Python; where the
    sign turned is told from a pair's nets in the order of the micro-batches."""
    given = F.when(F.col("p") < F.col("q"), F.col("up") - F.col("down")).otherwise(F.col("down") - F.col("up"))
    rows = transfers.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), given.alias("g"))
    nets = drain(rows.groupBy("a", "b").agg(F.sum("g").alias("net")), "update", every=True)
    before = F.coalesce(F.lag("net").over(Window.partitionBy("a", "b").orderBy("number")), F.lit(0))
    return nets.select("a", "b", "net", (F.signum(before) * F.signum("net") < 0).alias("flipped"))

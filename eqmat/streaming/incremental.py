"""Facts that come as a stream: each micro-batch extends the materialisation. Its state are tables, not operator state.

Batches may come in any order and again: facts are a set and the fixpoint only grows, so late and repeated facts are
harmless.
"""

from __future__ import annotations

import json
from collections.abc import Callable
from contextlib import nullcontext

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from eqmat.operators.dictionary import encode, encode_terms, extend_terms, lookup
from eqmat.operators.facts import FactStore
from eqmat.operators.mapping import RepMap
from eqmat.operators.materialise import Materialisation, Options, extend, materialise_rewriting
from eqmat.plans.rules import Atom, Rule, Var
from eqmat.storage import path_of, reread, saved, under

MARKED = "s long, p long, o long"


class LiveMaterialisation:
    """A materialisation that grows by batches of named triples.

    With ``state``, a folder that outlives the session, its tables are saved there and each batch that was taken in
    leaves a manifest of them, named by the batch; one that starts on a folder with manifests goes on from the last. A
    batch is done when its manifest is there, so a batch that a stream delivers again after a restart is taken in again
    or passed over, and never lost.
    """

    def __init__(self, spark: SparkSession, rules: list[Rule], opts: Options | None = None, state: str | None = None):
        self.spark, self.named_rules, self.opts, self.state = spark, rules, opts or Options(measure=False), state
        self.terms: DataFrame | None = None
        self.mat: Materialisation | None = None
        self.last_batch = -1
        if state:
            self._reload()

    def add(self, triples: DataFrame) -> None:
        with under(self.state) if self.state else nullcontext():
            names = triples.select(F.explode(F.array("s", "p", "o")).alias("lexical"))
            if self.mat is None:
                own = sorted({c for r in self.named_rules for c in r.constants})
                self.terms = encode_terms(names.unionByName(self.spark.createDataFrame([(c,) for c in own], "lexical string")) if own else names)
                ids = lookup(self.terms, own)
                self.mat = materialise_rewriting(self.spark, encode(triples, self.terms), [r.map(lambda c: ids[c]) for r in self.named_rules], self.opts)
            else:
                self.terms = extend_terms(self.terms, names)
                self.mat = extend(self.mat, encode(triples, self.terms))

    def on_batch(self, triples: DataFrame, batch_id: int) -> None:
        """For foreachBatch: a batch that is delivered again is passed over."""
        if batch_id > self.last_batch:
            self.add(triples)
            self.last_batch = batch_id
            if self.state:
                self._keep()

    def _keep(self) -> None:
        """Write the manifest of this batch: paths of the tables, the program and a few numbers."""
        m, places = self.mat, lambda pairs: [(path_of(df), n) for df, n in pairs]
        rows = m.rep_map.rows
        if path_of(rows) is None:  # nothing has been merged yet
            with under(self.state):
                rows = m.rep_map.rows = saved(rows, "rep_map")
        text = json.dumps({
            "batch": self.last_batch, "terms": path_of(self.terms), "layers": places(m.store.layers), "marked": places(m.store.marked), "dropped": m.store.dropped,
            "map": [path_of(rows), m.rep_map.n], "next_born": m.next_born, "neq": m.neq, "consistent": m.consistent, "derivations": m.by_rule,
            "rules": [[[x.name if isinstance(x, Var) else int(x) for x in atom.terms] for atom in (r.head, *r.body)] + [r.name] for r in m.rules],
        })
        self.spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.state}/manifest/batch={self.last_batch}")

    def _reload(self) -> None:
        jvm = self.spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(f"{self.state}/manifest")
        if not at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at):
            return
        done = self.spark.read.text(f"{self.state}/manifest").select("value").collect()  # one row a batch
        found = max((json.loads(r["value"]) for r in done), key=lambda x: x["batch"], default=None)
        if found is None:
            return
        read = lambda path, schema: reread(self.spark, path, schema)
        self.last_batch, self.terms = found["batch"], read(found["terms"], "id long, lexical string, num double")
        store = FactStore(self.spark)
        store.layers = [(read(path, "s long, p long, o long, born int, pb int"), n) for path, n in found["layers"]]
        store.marked = [(read(path, MARKED), n) for path, n in found["marked"]]
        store.dropped = found["dropped"]
        term = lambda x: Var(x) if isinstance(x, str) else x
        rules = [Rule(*(lambda head, *body: (head, body))(*[Atom(*map(term, a)) for a in r[:-1]]), r[-1]) for r in found["rules"]]
        self.mat = Materialisation(self.spark, store, RepMap(read(found["map"][0], "member long, rep long"), found["map"][1]), rules, by_rule=found["derivations"], consistent=found["consistent"], options=self.opts, next_born=found["next_born"], neq=found["neq"])


def materialise_stream(stream: DataFrame, to_triples: Callable[[DataFrame], DataFrame], live: LiveMaterialisation, checkpoint: str) -> StreamingQuery:
    """Feed a streaming DataFrame into ``live``."""
    return stream.writeStream.option("checkpointLocation", checkpoint).foreachBatch(lambda df, i: live.on_batch(to_triples(df), i)).trigger(availableNow=True).start()


def merges_per_window(equalities: DataFrame, kind: str = "tumbling", late: str = "10 minutes") -> DataFrame:
    """Equalities (ts, s, o) of two resources by window of event time, under a watermark."""
    return events_per_window(equalities.where("s <> o").select("ts", F.col("s").alias("user_id")), kind, late).withColumnRenamed("n", "merges").drop("users")


def as_of(events: DataFrame, facts: DataFrame) -> DataFrame:
    """events(user_id, event_id, ts) with the last fact of facts(user_id, ts, value) at or before each, null without one.
    Both sides are cut to days; a fact is also carried to later days as the last one of its day, so no user's history is
    put in one place: the join meets a day's facts and one row for each earlier day that has any."""
    day = lambda c: F.to_date(c)
    e = events.select("user_id", "event_id", F.col("ts").alias("at")).withColumn("day", day("at"))
    f = facts.select("user_id", F.col("ts").alias("since"), "value").withColumn("day", day("since"))
    last = f.groupBy("user_id", "day").agg(F.max_by(F.struct("since", "value"), F.struct("since", "value")).alias("f"))
    before = e.select("user_id", "day").distinct().join(last.withColumnRenamed("day", "own"), "user_id").where("own < day").groupBy("user_id", "day").agg(F.max_by("f", "own").alias("f"))
    same = e.join(f, ["user_id", "day"]).where("since <= at").groupBy("event_id").agg(F.max(F.struct("since", "value")).alias("g"))
    out = e.join(before, ["user_id", "day"], "left").join(same, "event_id", "left")
    return out.select("event_id", "user_id", F.coalesce("g.since", "f.since").alias("since"), F.coalesce("g.value", "f.value").alias("value"))


def events_per_window(events: DataFrame, kind: str = "tumbling", late: str = "10 minutes") -> DataFrame:
    """Events and distinct users (estimated) by window of event time, under a watermark."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    window = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "30 minutes")}[kind]
    return ts.groupBy(window.alias("w")).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users")).select("w.start", "w.end", "n", "users")


def events_within(events: DataFrame, seconds: int) -> DataFrame:
    """Pairs (earlier, later) of events of one user at most so many seconds apart: a range join made an equality join on
    time buckets of that width, where a pair lies in one bucket or in neighbours."""
    e = events.select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = seconds * 1_000_000
    a = e.select("user_id", F.col("event_id").alias("earlier"), F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)).alias("bucket"))
    b = e.select("user_id", F.col("event_id").alias("later"), F.col("t").alias("tb"), F.floor(F.col("t") / width).alias("bucket"))
    near = (F.col("tb") - F.col("ta")).between(0, width) & ((F.col("ta") < F.col("tb")) | (F.col("earlier") < F.col("later")))
    return a.join(b, ["user_id", "bucket"]).where(near).select("user_id", "earlier", "later")

"""The experiment workloads on the given tables, and how they are run in each mode."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqmat.operators.dictionary import encode, encode_terms, lookup
from eqmat.operators.materialise import MODES, Materialisation, Options
from eqmat.plans.rules import EQ, NEQ, Rule, parse_rules
from eqmat.sources.triples import constants, resource, triples_from
from eqmat.storage import saved, table


@dataclass
class Workload:
    name: str
    facts: DataFrame  # s, p, o as names
    rules: list[Rule]
    order: list[str] = field(default_factory=list)


@dataclass
class Run:
    mat: Materialisation
    terms: DataFrame


def _all(*parts: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _rules(text: str) -> list[Rule]:
    return parse_rules(text)[0]


def _nation_aliases(spark: SparkSession) -> DataFrame:
    return constants(spark, [(f"nation/{i:012d}", EQ, f"nation/{i + 20:012d}") for i in range(5)])


def duplicate_documents(spark, sf_dir) -> Workload:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    doc = resource("doc", F.col("doc_id"))
    facts = _all(
        triples_from(docs, doc, {"hasText": F.concat(F.lit("text/"), F.sha2("text", 256)), "inLang": F.concat(F.lit("lang/"), "lang"), "fromSource": F.concat(F.lit("source/"), "source")}),
        triples_from(labels, doc, {"quality": F.concat(F.lit("quality/"), F.col("quality").cast("string"))}),
    )
    return Workload("w1", facts, _rules("?x = ?y <- ?x hasText ?t, ?y hasText ?t\n?x sharesSource ?y <- ?x fromSource ?u, ?y fromSource ?u, ?x quality quality/0, ?y quality quality/0\n?x hasQuality ?q <- ?x = ?y, ?y quality ?q"))


def part_catalogue(spark, sf_dir) -> Workload:
    part, line = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem")
    key = F.concat_ws("|", "p_name", "p_brand", "p_type")
    l_key = F.concat(F.lit("line/"), F.xxhash64(*[F.col(c) for c in sorted(line.columns)]).cast("string"))
    facts = _all(
        triples_from(part, resource("part", F.col("p_partkey")), {"nameKey": F.concat(F.lit("key/"), key), "hasBrand": F.col("p_brand")}),
        triples_from(line, l_key, {"ofPart": resource("part", F.col("l_partkey")), "bySupplier": resource("supplier", F.col("l_suppkey"))}),
    )
    return Workload("w2", facts, _rules("?x = ?y <- ?x nameKey ?n, ?y nameKey ?n\n?s supplies ?x <- ?l ofPart ?x, ?l bySupplier ?s"))


def also_supplied(spark, sf_dir) -> Workload:
    """The catalogue with its third rule, all pairs of suppliers of a part: as many rows as it derives, by what it says."""
    w = part_catalogue(spark, sf_dir)
    return Workload("w2_also", w.facts, [*w.rules, *_rules("?x alsoSuppliedBy ?t <- ?s supplies ?x, ?t supplies ?x")])


def customer_households(spark, sf_dir) -> Workload:
    cust, orders = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    c = resource("customer", F.col("c_custkey"))
    facts = _all(
        triples_from(cust, c, {"household": F.concat(F.lit("home/"), F.col("c_nationkey").cast("string"), F.lit("/"), F.col("c_mktsegment"))}),
        triples_from(orders, resource("order", F.col("o_orderkey")), {"placedBy": resource("customer", F.col("o_custkey"))}),
    )
    return Workload("w3", facts, _rules("?x = ?y <- ?x household ?h, ?y household ?h\n?h owns ?o <- ?o placedBy ?x, ?x household ?h"))


def many_rules(spark, sf_dir) -> Workload:
    """One rule for each brand, type and size that occurs: all of one shape, held as rows."""
    part = table(spark, sf_dir, "part")
    names = [tuple(r) for r in part.select("p_brand", "p_type").distinct().orderBy("p_brand", "p_type").collect()]  # the program: at most brands x types
    facts = _all(triples_from(part, resource("part", F.col("p_partkey")), {"hasBrand": F.concat(F.lit("brand/"), "p_brand"), "hasType": F.concat(F.lit("ptype/"), "p_type")}), constants(spark, [("brand/Brand#11", EQ, "brand/Brand#12")]))
    return Workload("w3_rules", facts, [r for b, t in names for r in _rules(f"?x <class/{b} {t}> ?x <- ?x hasBrand <brand/{b}>, ?x hasType <ptype/{t}>")])


def vector_clusters(spark, sf_dir) -> Workload:
    e = table(spark, sf_dir, "embeddings")
    return Workload("w3b", triples_from(e, resource("vec", F.col("vec_id")), {"inCluster": F.concat(F.lit("cluster/"), F.col("label").cast("string"))}), _rules("?x = ?y <- ?x inCluster ?c, ?y inCluster ?c"))


def _places(spark, sf_dir, *tables: str) -> DataFrame:
    parts = [_nation_aliases(spark)]
    if "nation" in tables:
        parts.append(triples_from(table(spark, sf_dir, "nation"), resource("nation", F.col("n_nationkey")), {"inRegion": resource("region", F.col("n_regionkey"))}))
    if "customer" in tables:
        parts.append(triples_from(table(spark, sf_dir, "customer"), resource("customer", F.col("c_custkey")), {"inNation": resource("nation", F.col("c_nationkey"))}))
    if "supplier" in tables:
        parts.append(triples_from(table(spark, sf_dir, "supplier"), resource("supplier", F.col("s_suppkey")), {"inNation": resource("nation", F.col("s_nationkey"))}))
    if "orders" in tables:
        parts.append(triples_from(table(spark, sf_dir, "orders"), resource("order", F.col("o_orderkey")), {"placedBy": resource("customer", F.col("o_custkey"))}))
    return _all(*parts)


def nation_aliases(spark, sf_dir) -> Workload:
    return Workload("w4", _places(spark, sf_dir, "nation", "customer", "supplier", "orders"), _rules("?x custRegion ?r <- ?x inNation ?n, ?n inRegion ?r\n?o soldIn ?r <- ?o placedBy ?x, ?x custRegion ?r"))


def nation_regions(spark, sf_dir) -> Workload:
    """The rule on regions feeding itself: whatever is in something that is in a region is in that region."""
    w = nation_aliases(spark, sf_dir)
    return Workload("w4_recursive", w.facts, _rules("?x inRegion ?r <- ?x inNation ?n, ?n inRegion ?r\n?o soldIn ?r <- ?o placedBy ?x, ?x inRegion ?r"))


def supplier_hometown(spark, sf_dir) -> Workload:
    return Workload("w5", _places(spark, sf_dir, "supplier"), _rules("?x sharesNation ?y <- ?x inNation ?n, ?y inNation ?n\n?y sharesNation ?x <- ?x sharesNation ?y\n?x sharesNation ?z <- ?x sharesNation ?y, ?y sharesNation ?z"))


def page_mirrors(spark, sf_dir) -> Workload:
    url = F.regexp_replace(F.regexp_replace(F.lower("url"), r"^https?://(www\.|m\.)?", ""), r"[?#].*$", "")
    facts = triples_from(table(spark, sf_dir, "pages"), resource("page", F.col("page_id")), {"canonicalUrl": F.concat(F.lit("url/"), url)})
    return Workload("w6", facts, _rules("?x = ?y <- ?x canonicalUrl ?u, ?y canonicalUrl ?u"))


def event_facts(events: DataFrame) -> DataFrame:
    key = F.concat(F.lit("device/"), F.get_json_object("props", "$.k"), F.lit("|"), F.col("value").cast("decimal(20,6)").cast("string"))
    return triples_from(events, resource("event", F.col("event_id")), {"byUser": resource("user", F.col("user_id")), "deviceKey": key})


EVENT_RULES = "?u = ?v <- ?e byUser ?u, ?f byUser ?v, ?e deviceKey ?d, ?f deviceKey ?d"


def event_identities(spark, sf_dir, purchases: bool = True) -> Workload:
    e = table(spark, sf_dir, "events")
    return Workload("w7" if purchases else "w7_all", event_facts(e.where("event_type = 'purchase'") if purchases else e), _rules(EVENT_RULES))


def rule_constants_merged(spark, sf_dir) -> Workload:
    """Rules that name nations which are retired: nothing follows unless the rules are rewritten too."""
    facts = _all(_places(spark, sf_dir, "nation", "supplier"), constants(spark, [("customer/000000000001", "homeOf", "nation/000000000021")]))
    return Workload("w8", facts, _rules("?s localTo home <- ?s inNation nation/000000000020\n?x = customer/000000000000 <- ?x homeOf nation/000000000021"))


def contradiction_check(spark, sf_dir) -> Workload:
    w = vector_clusters(spark, sf_dir)
    ends = table(spark, sf_dir, "embeddings").where("label = 0").agg(F.min("vec_id").alias("a"), F.max("vec_id").alias("b"))
    clash = ends.select(resource("vec", F.col("a")).alias("s"), F.lit(NEQ).alias("p"), resource("vec", F.col("b")).alias("o"))
    return Workload("w9", w.facts.unionByName(clash), w.rules)


def consistent_labels(spark, sf_dir) -> Workload:
    w = duplicate_documents(spark, sf_dir)
    return Workload("w9_consistent", w.facts.unionByName(constants(spark, [("quality/0", NEQ, "quality/1")])), [w.rules[0], *_rules("?q = ?r <- ?x quality ?q, ?x quality ?r")])


def user_customer_link(spark, sf_dir) -> Workload:
    events, cust, orders = (table(spark, sf_dir, n) for n in ("events", "customer", "orders"))
    users = events.select("user_id").distinct().join(cust, F.col("user_id") == F.col("c_custkey"))
    link = users.select(resource("user", F.col("user_id")).alias("s"), F.lit(EQ).alias("p"), resource("customer", F.col("user_id")).alias("o"))
    facts = _all(
        link,
        triples_from(events, resource("event", F.col("event_id")), {"byUser": resource("user", F.col("user_id")), "kind": F.concat(F.lit("kind/"), "event_type")}),
        triples_from(orders, resource("order", F.col("o_orderkey")), {"placedBy": resource("customer", F.col("o_custkey"))}),
    )
    return Workload("w10", facts, _rules("?c activeOn ?t <- ?e byUser ?c, ?e kind ?t\n?o byActive ?t <- ?o placedBy ?c, ?c activeOn ?t"))


def predicate_alias(spark, sf_dir) -> Workload:
    orders = table(spark, sf_dir, "orders")
    facts = triples_from(orders, resource("order", F.col("o_orderkey")), {"placedBy": resource("customer", F.col("o_custkey"))})
    return Workload("w11", facts.unionByName(constants(spark, [("placedBy", EQ, "boughtBy")])), _rules("?b hasOrder ?o <- ?o boughtBy ?b"))


EXAMPLE = """
?x = USA <- Obama presidentOf ?x
?x = Obama <- ?x presidentOf USA
USPresident presidentOf US
Obama presidentOf America
Obama presidentOf US
"""


def worked_example(spark, sf_dir="", order=("presidentOf", "US", "USA", "America", "Obama", "USPresident")) -> Workload:
    rules, facts = parse_rules(EXAMPLE)
    return Workload("example" if order[1] == "US" else "example_usa", constants(spark, [a.terms for a in facts]), rules, list(order))


def example_with_usa(spark, sf_dir="") -> Workload:
    """The same with USA before US, so that USA represents them."""
    return worked_example(spark, sf_dir, ("presidentOf", "USA", "US", "America", "Obama", "USPresident"))


def last_order(spark, sf_dir) -> tuple[str, str]:
    """Names of the last order and of the last customer that has ordered."""
    row = table(spark, sf_dir, "orders").agg(F.max("o_orderkey").alias("o"), F.max("o_custkey").alias("c"))
    return tuple(row.select(resource("order", F.col("o")), resource("customer", F.col("c"))).first())


def equal_orders(spark, sf_dir) -> Workload:
    """The rules of the worked example on the orders: whoever placed the last order is the last customer, and whatever that
    customer placed is the last order. Both constants are retired by smaller names, so the rules must be rewritten."""
    order, customer = last_order(spark, sf_dir)
    facts = triples_from(table(spark, sf_dir, "orders"), resource("order", F.col("o_orderkey")), {"placedBy": resource("customer", F.col("o_custkey"))})
    return Workload("equal_orders", facts, _rules(f"?x = {customer} <- {order} placedBy ?x\n?x = {order} <- ?x placedBy {customer}"))


WORKLOADS = {
    "equal_orders": equal_orders,
    "w1": duplicate_documents, "w2": part_catalogue, "w2_also": also_supplied, "w4_recursive": nation_regions, "w3": customer_households, "w3_rules": many_rules, "w3b": vector_clusters, "w4": nation_aliases, "w5": supplier_hometown,
    "w6": page_mirrors, "w7": event_identities, "w7_all": lambda s, d: event_identities(s, d, False), "w8": rule_constants_merged, "w9": contradiction_check,
    "w9_consistent": consistent_labels, "w10": user_customer_link, "w11": predicate_alias, "example": worked_example, "example_usa": example_with_usa,
}

_RUNS: dict[tuple, Run] = {}
MOST_RUNS = 64


def run(workload: Workload, mode: str = "rew", opts: Options | None = None, **more) -> Run:
    """Encode a workload and materialise it."""
    return run_encoded(encoded(workload), mode, opts, **more)


def run_encoded(both: tuple[DataFrame, DataFrame, list[Rule]], mode: str = "rew", opts: Options | None = None, **more) -> Run:
    facts, terms, rules = both
    return Run(MODES[mode](facts.sparkSession, facts, rules, opts, **more), terms)


def encoded(workload: Workload) -> tuple[DataFrame, DataFrame, list[Rule]]:
    """Facts of ids, the dictionary and rules of ids."""
    spark = workload.facts.sparkSession
    own = sorted({c for r in workload.rules for c in r.constants})
    facts = saved(workload.facts.distinct(), "given")
    names = facts.select(F.explode(F.array("s", "p", "o")).alias("lexical"))
    if own:
        names = names.unionByName(spark.createDataFrame([(c,) for c in own], "lexical string"))
    terms = encode_terms(names, workload.order)
    ids = lookup(terms, own)
    rules = [r.map(lambda c: ids[c]) for r in workload.rules]
    return encode(facts, terms), terms, rules


def run_named(spark: SparkSession, sf_dir: str, name: str, mode: str = "rew") -> Run:
    """A workload by name; queries on one materialisation in one session share it."""
    return runs_named(spark, sf_dir, name, (mode,))[0]


def runs_named(spark: SparkSession, sf_dir: str, name: str, modes: tuple[str, ...], **options) -> list[Run]:
    """A workload by name in several modes, encoded once for those that have not been run."""
    both, out = None, []
    for mode in modes:
        key = (spark.sparkContext.applicationId, sf_dir, name, mode, *sorted(options.items()))
        if key not in _RUNS:
            while len(_RUNS) >= MOST_RUNS:  # the oldest goes
                _RUNS.pop(next(iter(_RUNS)))
            both = both or encoded(WORKLOADS[name](spark, sf_dir))
            _RUNS[key] = run_encoded(both, mode, Options(**options))
        out.append(_RUNS[key])
    return out

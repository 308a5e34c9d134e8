"""Mixing sources to target weights by hierarchical budgets.

Weights go down a tree domain - language - source; every node gives its budget to its children by weight.
What a child cannot fill (its stock times the epochs allowed) goes to its siblings, again by weight, before anything
is left for the ancestors' other children. Each leaf then takes a token prefix of its documents, in a seeded order, epoch after epoch.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, prefix_sums, unused
from .packing import n_words


@dataclass
class Node:
    weight: float = 1.0
    stock: int = 0  # of a leaf: tokens it can give, all epochs taken together
    children: dict[str, "Node"] = field(default_factory=dict)
    budget: int = 0

    def capacity(self) -> int:
        return sum(c.capacity() for c in self.children.values()) if self.children else self.stock


def share(node: Node, budget: int) -> None:
    """Sets the budgets below a node. Children that can't use their part get what they have, and the rest is dealt
    again to the others by weight; whole tokens by largest remainder, so budgets add up exactly."""
    node.budget = min(budget, node.capacity())
    if not node.children:
        return
    left, open_ = node.budget, {k: c for k, c in node.children.items() if c.capacity()}
    given = dict.fromkeys(node.children, 0)
    while open_:
        total = sum(c.weight for c in open_.values())
        weight = {k: c.weight / total if total > 0 else 1 / len(open_) for k, c in open_.items()}
        full = [k for k, c in open_.items() if weight[k] * left >= c.capacity()]
        if not full:
            parts = {k: int(w * left) for k, w in weight.items()}
            spare = left - sum(parts.values())
            for k in sorted(parts, key=lambda k: (parts[k] - weight[k] * left, k))[:spare]:
                parts[k] += 1
            given.update(parts)
            break
        for k in full:
            given[k] = open_.pop(k).capacity()
            left -= given[k]
    for k, c in node.children.items():
        share(c, given[k])


def domain_of(source):
    """The domain of a source column 'srcN' by its number: a parameter of the production mix."""
    n = F.coalesce(F.regexp_extract(source, r"(\d+)$", 1), F.lit(""))
    n = F.when(n == "", F.lit(-1)).otherwise(n.cast("int"))
    return F.when(n.between(0, 6), "web").when(n.between(7, 12), "books").when(n.between(13, 19), "reference").otherwise("other")


#: The production weights; a name that isn't listed weighs 1 (sources alike).
DOMAIN_WEIGHTS = {"web": 0.5, "books": 0.3, "reference": 0.2, "other": 0.05}
LANGUAGE_WEIGHTS = {"en": 0.55, "de": 0.15, "fr": 0.15, "es": 0.15}


def budgets(stock: list[tuple[str, str, str, int]], target: int | float, epochs: int, domain_weights: dict, language_weights: dict, source_weights: dict) -> dict[tuple[str, str, str], int]:
    """Tokens each leaf (domain, language, source) is to give; target: tokens, or a share of one epoch's stock."""
    root = Node()
    for d, lang, s, tokens in sorted(stock):
        dn = root.children.setdefault(d, Node(domain_weights.get(d, 1.0)))
        ln = dn.children.setdefault(lang, Node(language_weights.get(lang, 1.0)))
        ln.children[s] = Node(source_weights.get(s, 1.0), tokens * epochs)
    total = sum(x[3] for x in stock)
    share(root, round(target * total) if isinstance(target, float) else target)
    return {(d, lang, s): leaf.budget for d, dn in root.children.items() for lang, ln in dn.children.items() for s, leaf in ln.children.items()}


def mix(docs: DataFrame, target: int | float = 0.8, epochs: int = 4, seed: int = 17, id_col: str = "doc_id", text: str = "text", lang: str = "lang", source: str = "source", domain=domain_of, domain_weights: dict = DOMAIN_WEIGHTS, language_weights: dict = LANGUAGE_WEIGHTS, source_weights: dict | None = None) -> DataFrame:
    """(id, domain, lang, source, n_tokens, epoch, start) of the picks: a row for each time a document is taken.

    A leaf of budget b takes whole rounds over its stock, then the prefix of one more, up to the document in which token b
    lies; start is the leaf's tokens before the pick. Each epoch has its own seeded order of ids. Null languages and
    sources are leaves named ''; null and empty texts count one token; repeated rows are stock each; an empty table gives no rows.
    Leaves (a row each) are all that reaches the driver; a leaf of any size is ordered over many tasks.
    """
    name = lambda c: F.coalesce(F.col(c), F.lit(""))
    sized = docs.select(F.col(id_col).alias("_id"), name(lang).alias("_lang"), name(source).alias("_source"), F.greatest(n_words(F.col(text)), F.lit(1)).alias("n_tokens")).withColumn("_domain", domain(F.col("_source")))
    sized = cut(sized)
    leaf = ["_domain", "_lang", "_source"]
    stock = [tuple(r) for r in sized.groupBy(*leaf).agg(F.sum("n_tokens")).collect()]
    plan = budgets(stock, target, epochs, domain_weights, language_weights, source_weights or {})
    spark = docs.sparkSession
    rows = [(d, lg, s, plan[d, lg, s], t) for d, lg, s, t in stock if plan[d, lg, s]]
    told = spark.createDataFrame(rows, "_domain string, _lang string, _source string, _budget long, _stock long")
    held = sized.join(F.broadcast(told), leaf)  # a row for each leaf, as collected above
    last = F.floor((F.col("_budget") - 1) / F.col("_stock")).cast("int")
    epoch = held.withColumn("_epoch", F.explode(F.sequence(F.lit(0), last))).withColumn("_h", F.xxhash64("_id", F.lit(seed), "_epoch"))
    summed = prefix_sums(epoch, [*leaf, "_epoch"], ["_h", "_id"], "n_tokens", "_before")
    start = F.col("_epoch") * F.col("_stock") + F.col("_before")
    return summed.where(start < F.col("_budget")).select(F.col("_id").alias(id_col), F.col("_domain").alias("domain"), F.col("_lang").alias("lang"), F.col("_source").alias("source"), "n_tokens", F.col("_epoch").alias("epoch"), start.alias("start"))


def take_mix(docs: DataFrame, target: int | float = 0.9, id_col: str = "doc_id", **options) -> DataFrame:
    """docs, all columns, with each document as often as the mix picks it (options as in mix; one epoch if none is named).

    Repeated rows of one id are all kept when the id is picked, and rows without an id count as such repeats. Null texts,
    languages and sources are as in mix; columns of any names pass through; an empty table gives no rows.
    """
    key, last, again = (unused(n, docs.columns) for n in ("_key", "_last", "_again"))
    picks = mix(docs, target, id_col=id_col, **{"epochs": 1, **options})
    times = picks.groupBy(F.col(id_col).alias(key)).agg(F.max("epoch").alias(last))
    taken = docs.join(times, F.col(id_col).eqNullSafe(F.col(key)))
    return taken.withColumn(again, F.explode(F.sequence(F.lit(0), F.col(last)))).drop(key, last, again)

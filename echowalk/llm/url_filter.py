"""URL filter: host and path rules, and gradient-boosted trees for the rest.

Only DataFrame and SQL functions run on data. Trees are grown from histograms:
one aggregation per level gives (node, feature, bin) sums of gradients, at most
nodes x features x bins rows, and the driver reads the best splits off them.
Gradients are summed as scaled integers, so the order of rows cannot change a
split.

Defined results: a null url, or one without ``://``, has empty host and path
and no rule; without labelled urls of both classes the method allows all;
rows with equal ids each get their row; an empty table gives no rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stash

#: Fixed values: (rule, verdict).
RULES = (("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block"))

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_SCALE = 1 << 20


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^([^/?#]*)", 1), _UPPER, _LOWER)
    return host, F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; nulls if none fits."""
    rule = verdict = None
    for text, says in sorted(rules, key=lambda r: (-len(r[0]), r[0])):
        name, slash, rest = text.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        rule = F.when(fits, text) if rule is None else rule.when(fits, text)
        verdict = F.when(fits, says) if verdict is None else verdict.when(fits, says)
    return rule.cast("string"), verdict.cast("string")


LEXICAL = ("url_chars", "host_chars", "depth", "digit_ratio", "entropy", "params", "marks", "labels")


def lexical(df: DataFrame) -> DataFrame:
    """Adds the features of ``url``, ``host`` and ``path``."""
    url = F.coalesce(F.col("url"), F.lit(""))
    n = F.length(url)
    others = lambda pattern: F.length(F.regexp_replace(url, pattern, ""))
    df = df.withColumns(
        {
            "url_chars": n.cast("double"),
            "host_chars": F.length("host").cast("double"),
            "depth": F.size(F.filter(F.split("path", "/"), lambda x: x != "")).cast("double"),
            "digit_ratio": ((n - others("[0-9]")) / F.greatest(n, F.lit(1))).cast("double"),
            "params": (n - others("[=&;]")).cast("double"),
            "marks": (n - others("[-_.~%@+]")).cast("double"),
            "labels": F.size(F.split("host", "\\.")).cast("double"),
            "_signs": F.transform(F.array_distinct(F.split(url, "")), lambda c: (n - F.length(F.replace(url, c, F.lit("")))).cast("double")),
            "suffix": F.concat(F.substring_index("host", ".", -1), F.lit("/"), F.regexp_extract("path", "^/([^/]{0,8})", 1)),
        }
    )
    spread = F.aggregate("_signs", F.lit(0.0), lambda a, x: a + F.when(x > 0, x * F.log2(x)).otherwise(0.0))
    return df.withColumn("entropy", F.when(F.col("url_chars") > 0, F.log2("url_chars") - spread / F.col("url_chars")).otherwise(0.0)).drop("_signs")


@dataclass
class Leaf:
    value: float


@dataclass
class Split:
    feature: str
    cut: float  # left: at most this
    left: object = None
    right: object = None


@dataclass
class Model:
    start: float = 0.0
    trees: list = field(default_factory=list)
    suffixes: DataFrame | None = None
    prior: float = 0.5

    def margin(self) -> Column:
        out = F.lit(self.start)
        for tree in self.trees:
            out = out + _value(tree)
        return out

    def with_suffix_rate(self, df: DataFrame) -> DataFrame:
        """The table of suffixes has as many rows as the sample of labelled urls at most."""
        if self.suffixes is None:
            return df.withColumn("suffix_rate", F.lit(self.prior))
        return df.join(F.broadcast(self.suffixes), "suffix", "left").withColumn("suffix_rate", F.coalesce("suffix_rate", F.lit(self.prior)))


def _value(node) -> Column:
    if isinstance(node, Leaf):
        return F.lit(node.value)
    return F.when(F.col(node.feature) <= node.cut, _value(node.left)).otherwise(_value(node.right))


def fit(labelled: DataFrame, trees: int = 8, depth: int = 3, bins: int = 16, rate: float = 0.4, l2: float = 1.0, sample: int = 20_000) -> Model:
    """Boosted trees for ``blocked`` (boolean) from features of ``lexical``. The labelled rows are
    thinned by a hash of the url to about ``sample``, the bound of all that training holds."""
    n = labelled.count()
    if not n:
        return Model(start=-10.0)
    keep = min(1.0, sample / n)
    thin = labelled.filter(F.pmod(F.xxhash64("url", F.lit("thin")), F.lit(1 << 30)) <= int(keep * (1 << 30)))
    thin = stash(lexical(thin).select(*LEXICAL, "suffix", F.col("blocked").cast("long").alias("y")).repartition(4), "labelled-urls")
    total, blocked = thin.agg(F.count("*"), F.coalesce(F.sum("y"), F.lit(0))).first()
    if blocked in (0, total):
        return Model(start=10.0 if blocked and blocked == total else -10.0)
    prior = blocked / total
    suffixes = stash(thin.groupBy("suffix").agg(((F.sum("y") + 4 * prior) / (F.count("*") + 4)).alias("suffix_rate")), "url-suffixes")
    model = Model(math.log(prior / (1 - prior)), [], suffixes, prior)
    names = [*LEXICAL, "suffix_rate"]
    rows = model.with_suffix_rate(thin)
    cuts = [sorted(set(c)) for c in rows.approxQuantile(names, [k / bins for k in range(1, bins)], 0.005)]
    bin_of = lambda f, c: sum((F.when(F.col(f) > x, 1).otherwise(0) for x in c), F.lit(0)).cast("int")
    rows = stash(rows.withColumn("binned", F.array(*(bin_of(f, c) for f, c in zip(names, cuts)))), "binned-urls")
    for _ in range(trees):
        root = Split("", 0.0)
        open_nodes = [(root, "left")]
        for level in range(depth + 1):
            held = _histogram(rows, model, root.left, len(open_nodes))
            following = []
            for at, (parent, side) in enumerate(open_nodes):
                node = _best(held.get(at, {}), names, cuts, l2, rate, level == depth)
                setattr(parent, side, node)
                if isinstance(node, Split):
                    following += [(node, "left"), (node, "right")]
            open_nodes = following
            if not open_nodes:
                break
        model.trees.append(root.left)
    return model


def _node_of(tree, counter: list[int]) -> Column:
    """The number of the open node (in order of depth-first walk) that a row reaches; -1: a leaf."""
    if tree is None:
        counter[0] += 1
        return F.lit(counter[0] - 1)
    if isinstance(tree, Leaf):
        return F.lit(-1)
    return F.when(F.col(tree.feature) <= tree.cut, _node_of(tree.left, counter)).otherwise(_node_of(tree.right, counter))


def _histogram(rows: DataFrame, model: Model, tree, nodes: int) -> dict:
    p = 1 / (1 + F.exp(-model.margin()))
    scaled = lambda c: F.round(c * _SCALE).cast("long")
    found = (
        rows.withColumns({"node": _node_of(tree, [0]), "_p": p})
        .filter("node >= 0")
        .select("node", scaled(F.col("_p") - F.col("y")).alias("g"), scaled(F.col("_p") * (1 - F.col("_p"))).alias("h"), F.posexplode("binned").alias("feature", "bin"))
        .groupBy("node", "feature", "bin")
        .agg(F.sum("g").alias("g"), F.sum("h").alias("h"))
    )
    out: dict = {}
    for r in found.collect():  # nodes x features x bins at most
        out.setdefault(r["node"], {})[r["feature"], r["bin"]] = (r["g"] / _SCALE, r["h"] / _SCALE)
    return out


def _best(sums: dict, names, cuts, l2: float, rate: float, last: bool):
    g = sum(v[0] for (f, _), v in sums.items() if f == 0)
    h = sum(v[1] for (f, _), v in sums.items() if f == 0)
    best = (1e-3, None, None)
    for f in range(len(names)) if not last else ():
        left_g = left_h = 0.0
        for b, cut in enumerate(cuts[f]):
            dg, dh = sums.get((f, b), (0.0, 0.0))
            left_g, left_h = left_g + dg, left_h + dh
            if min(left_h, h - left_h) < 1.0:
                continue
            gain = left_g**2 / (left_h + l2) + (g - left_g) ** 2 / (h - left_h + l2) - g * g / (h + l2)
            if gain > best[0] + 1e-9:
                best = (gain, f, cut)
    return Leaf(-rate * g / (h + l2)) if best[1] is None else Split(names[best[1]], best[2])


def filter_urls(df: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, **fit_options) -> DataFrame:
    """page_id, host, path, rule, verdict, score: the rule's verdict, or else the model's, which
    learns from the urls that rules label."""
    host, path = host_and_path(F.col("url"))
    pages = df.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url")).withColumns({"host": host, "path": path})
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    pages = pages.withColumns({"rule": rule, "by_rule": verdict})
    model = fit(pages.filter(F.col("by_rule").isNotNull()).withColumn("blocked", F.col("by_rule") == "block"), **fit_options)
    scored = model.with_suffix_rate(lexical(pages)).withColumn("score", 1 / (1 + F.exp(-model.margin())))
    by_model = F.when(F.col("score") > 0.5, "block").otherwise("allow")
    return scored.select("page_id", "host", "path", "rule", F.coalesce("by_rule", by_model).alias("verdict"), "score")

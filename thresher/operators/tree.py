"""Several attributes, stumps and deeper trees: one shared scan for all attributes and nodes of a level."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .curves import curve_of
from .held import hold
from .histogram import histogram


def long_form(df: DataFrame, features: Sequence[str], y: str, keep: Sequence[str] = ()) -> DataFrame:
    """(keep, attr, x, y): a row for each attribute of each row, expanded before the partial aggregate."""
    pairs = F.array(*[F.struct(F.lit(f).alias("attr"), F.col(f).cast("long").alias("x")) for f in features])
    return df.select(*keep, F.col(y).alias("y"), F.explode(pairs).alias("_p")).select(*keep, "_p.attr", "_p.x", "y").where("x is not null and y is not null")


def best_split(df: DataFrame, features: Sequence[str], y: str, criterion: str = "mse", scale: int = 1, by: Sequence[str] = (), digits: int = 6) -> DataFrame:
    """(by, attr, j, loss): the best attribute and split, in each group of ``by`` that can be split."""
    return split_or_leaf(df, features, y, criterion, scale, by, digits).where("b is not null").select(*by, "b.*")


def split_or_leaf(df: DataFrame, features: Sequence[str], y: str, criterion: str = "mse", scale: int = 1, by: Sequence[str] = (), digits: int = 6) -> DataFrame:
    """(by, b, leaf): the best split of each group (null without one), and the group as a leaf: loss, prediction, rows."""
    curve = attribute_curves(df, features, y, criterion, scale, by)
    rounded = curve.withColumn("loss", F.round("loss", digits))
    chosen = F.min_by(F.struct("attr", F.col("x").alias("j"), "loss", "n_left", "n_right", "pred_left", "pred_right"), F.when(F.col("n_right") > 0, F.struct("loss", "attr", "x")))
    # The split at an attribute's largest value leaves nothing on the right: that is the leaf.
    leaf = F.min_by(F.struct("loss", F.col("pred_left").alias("prediction"), F.col("n_left").alias("rows")), F.when(F.col("n_right") == 0, F.col("attr")))
    can = F.count_if(F.col("n_right") > 0) > 0
    return rounded.groupBy(*by).agg(F.when(can, chosen).alias("b"), leaf.alias("leaf"))


def per_attribute(df: DataFrame, features: Sequence[str], y: str, criterion: str = "mse", scale: int = 1, digits: int = 6) -> DataFrame:
    """(attr, j, loss): every attribute's best split."""
    curve = attribute_curves(df, features, y, criterion, scale).withColumn("loss", F.round("loss", digits))
    return curve.groupBy("attr").agg(F.min_by(F.struct(F.col("x").alias("j"), "loss"), F.struct("loss", "x")).alias("b")).select("attr", "b.j", "b.loss")


def attribute_curves(df: DataFrame, features: Sequence[str], y: str, criterion: str, scale: int, by: Sequence[str] = ()) -> DataFrame:
    obs = long_form(df, features, y, by)
    return curve_of(hold(histogram(obs, criterion, [*by, "attr"])), criterion, scale, [*by, "attr"])


@dataclass
class Node:
    number: int
    prediction: float | None = None
    loss: float | None = None
    rows: int = 0
    attr: str | None = None
    split: int | None = None
    children: list[Node] = field(default_factory=list)


def grow(df: DataFrame, features: Sequence[str], y: str, criterion: str = "mse", max_depth: int = 2, min_rows: int = 1, min_gain: float = 0.0, scale: int = 1, digits: int = 6) -> Node:
    """Top-down growth; a level is one job over the pruned columns, whatever the number of its nodes.

    A node is split if both sides have ``min_rows`` rows and the loss falls by ``min_gain`` at least. A node that
    is not split predicts its mean or majority, the root too.
    """
    root = Node(1)
    level = [root]
    for _ in range(max_depth):
        placed = df.select(*features, y, node_number(root).alias("node"))
        open_ = [n.number for n in level]
        found = {r.node: r for r in split_or_leaf(placed.where(F.col("node").isin(open_)), features, y, criterion, scale, ["node"], digits).collect()}
        after = []
        for node in level:
            r = found.get(node.number)
            if r is None:
                continue
            node.prediction, node.rows, node.loss = r.leaf.prediction, r.leaf.rows, r.leaf.loss
            if r.b is None or r.b.n_left < min_rows or r.b.n_right < min_rows or round(r.leaf.loss - r.b.loss, digits) < min_gain:
                continue
            node.attr, node.split, node.loss = r.b.attr, r.b.j, r.b.loss
            node.children = [Node(2 * node.number, r.b.pred_left, rows=r.b.n_left), Node(2 * node.number + 1, r.b.pred_right, rows=r.b.n_right)]
            after += node.children
        level = after
        if not level:
            break
    return root


def stump(df: DataFrame, features: Sequence[str], y: str, criterion: str = "misclassification", scale: int = 1) -> Node:
    return grow(df, features, y, criterion, 1, scale=scale)


def node_number(root: Node) -> Column:
    """A row's leaf as a nested case expression; rows without the attribute go right."""
    if not root.children:
        return F.lit(root.number)
    return F.when(F.col(root.attr) <= root.split, node_number(root.children[0])).otherwise(node_number(root.children[1]))


def predict(df: DataFrame, root: Node, name: str = "prediction") -> DataFrame:
    def value(n: Node) -> Column:
        if not n.children:
            return F.lit(n.prediction).cast("double")
        return F.when(F.col(n.attr) <= n.split, value(n.children[0])).otherwise(value(n.children[1]))

    return df.withColumn(name, value(root))


def splits_of(root: Node) -> list[tuple[int, str, int, float, int]]:
    """(node, attribute, split, loss, rows) of every inner node."""
    if not root.children:
        return []
    return [(root.number, root.attr, root.split, root.loss, root.rows), *splits_of(root.children[0]), *splits_of(root.children[1])]


def score(df: DataFrame, y: str, prediction: str = "prediction") -> DataFrame:
    """One row: mean squared error and, for labels of +1 and -1, error rate and confusion counts."""
    d = F.col(prediction) - F.col(y)
    p, t = F.col(prediction) > 0, F.col(y) > 0
    return df.agg(F.avg(d * d).alias("mse"), F.avg((p != t).cast("double")).alias("error"), F.count_if(p & t).alias("tp"), F.count_if(p & ~t).alias("fp"), F.count_if(~p & t).alias("fn"), F.count_if(~p & ~t).alias("tn"))

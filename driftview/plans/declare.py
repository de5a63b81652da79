"""Views declared in text.

    DEFINE MODEL VIEW name OVER entities KEY id LABELS labels(label)
    EXAMPLES examples(id, label) FEATURES function(column, option=value) [USING method] [POLICY eager|lazy] [ARCH disk|memory|hybrid]

Names are of tables or temporary views; feature functions and methods come from
their registries.  Without USING, the method of smallest leave-one-out error is
taken.
"""

from __future__ import annotations

import ast
import re
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions.features import get_feature
from driftview.learn.select import CLOSED, METHODS, get_method, method_for, select_method
from driftview.operators.multiclass_view import MulticlassView
from driftview.operators.view import ClassificationView, Options, computed_once, gather
from driftview.session import shared_path

_NAME = r"[A-Za-z_]\w*"
_GRAMMAR = re.compile(
    rf"^\s*DEFINE\s+MODEL\s+VIEW\s+(?P<name>{_NAME})\s+OVER\s+(?P<entities>{_NAME})\s+KEY\s+(?P<key>{_NAME})\s+LABELS\s+(?P<labels>{_NAME})\s*\(\s*(?P<label_set>{_NAME})\s*\)"
    rf"\s+EXAMPLES\s+(?P<examples>{_NAME})\s*\(\s*(?P<example_key>{_NAME})\s*,\s*(?P<label>{_NAME})\s*\)\s+FEATURES\s+(?P<feature>{_NAME})\s*\((?P<arguments>[^)]*)\)"
    rf"(?:\s+USING\s+(?P<method>{_NAME}))?(?:\s+POLICY\s+(?P<policy>{_NAME}))?(?:\s+ARCH\s+(?P<arch>{_NAME}))?\s*;?\s*$",
    re.IGNORECASE | re.DOTALL,
)


#: Labels that a view can have; each is a model, and each round trains them all.
MAX_CLASSES = 1000


@dataclass(frozen=True)
class ViewSpec:
    """Of two declared labels the larger is the positive class; of more, each is a class of its own."""

    name: str
    entities: str
    key: str
    labels: str
    label_set: str
    examples: str
    example_key: str
    label: str
    feature: str
    positional: tuple = ()
    options: dict = field(default_factory=dict)
    method: str | None = None
    policy: str = "eager"
    arch: str = "disk"


def parse_definition(text: str) -> ViewSpec:
    found = _GRAMMAR.match(text)
    if not found:
        raise ValueError("not a view definition: DEFINE MODEL VIEW … OVER … KEY … LABELS …(…) EXAMPLES …(…, …) FEATURES …(…) is expected")
    g = found.groupdict()
    positional, options = [], {}
    for part in filter(None, (p.strip() for p in g.pop("arguments").split(","))):
        key, eq, value = part.partition("=")
        if eq:
            options[key.strip()] = ast.literal_eval(value.strip())
        else:
            positional.append(part)
    g = {k: v for k, v in g.items() if v is not None}
    return ViewSpec(**{k: (v.lower() if k in ("method", "policy", "arch") else v) for k, v in g.items()}, positional=tuple(positional), options=options)


def _checked(spark: SparkSession, spec: ViewSpec) -> tuple[DataFrame, DataFrame, list]:
    """The entities, the examples with classes, and the labels, after the declaration's names were resolved."""
    entities, examples, labels = (spark.table(t) for t in (spec.entities, spec.examples, spec.labels))
    for df, column, where in ((entities, spec.key, spec.entities), (examples, spec.example_key, spec.examples), (examples, spec.label, spec.examples), (labels, spec.label_set, spec.labels)):
        if column not in df.columns:
            raise ValueError(f"{where} has no column {column}")
    declared = sorted(r[0] for r in labels.select(spec.label_set).distinct().limit(MAX_CLASSES + 1).collect() if r[0] is not None)
    if len(declared) < 2:
        raise ValueError(f"a view needs two labels at least, not {len(declared)}")
    if len(declared) > MAX_CLASSES:
        raise ValueError(f"more than {MAX_CLASSES} labels")
    marked = examples.select(F.col(spec.example_key).alias("id"), F.col(spec.label).alias("y")).where("id is not null and y is not null")
    if marked.where(~F.col("y").isin(declared)).limit(1).count():
        raise ValueError("an example has a label that is not declared")
    if marked.groupBy("id").count().where("count > 1").limit(1).count():
        raise ValueError("ids of examples are not unique")
    label = F.when(F.col("y") == declared[-1], 1).otherwise(-1) if len(declared) == 2 else F.col("y")
    return entities, marked.select("id", label.alias("label")), declared


def create_view(spark: SparkSession, spec: ViewSpec, options: Options | None = None) -> ClassificationView | MulticlassView:
    """Featurize, train, cluster and register the view under its name; more than two labels make a view of several classes."""
    entities, examples, declared = _checked(spark, spec)
    feature = get_feature(spec.feature, *spec.positional, **spec.options).fit(entities)
    vectors = computed_once(feature.transform(entities, spec.key), shared_path(spark, spec.name))
    if len(declared) > 2:
        return MulticlassView.create(vectors, examples, get_method(spec.method or "svm"), feature.dim, declared, options or Options(policy=spec.policy, arch=spec.arch), name=spec.name)
    method = spec.method or choose(spark, vectors, examples, feature.dim)
    counts = {r["label"]: r["count"] for r in examples.groupBy("label").count().collect()}  # two rows
    trainer = method_for(method, counts.get(-1, 0), counts.get(1, 0))
    return ClassificationView.create(vectors, examples, trainer, feature.dim, options or Options(policy=spec.policy, arch=spec.arch), name=spec.name)


#: Examples that the choice of a method leaves out in turn, and the dimensions up to which closed forms take part.
CHOICE_EXAMPLES, CHOICE_DIM = 200, 512


def choose(spark: SparkSession, entities: DataFrame, examples: DataFrame, dim: int) -> str:
    """The method of smallest leave-one-out error on the first CHOICE_EXAMPLES examples by id.

    Of vectors with more than CHOICE_DIM dimensions, only the gradient methods are compared.
    """
    batch = [(f, y) for _, f, y in gather(entities, examples.orderBy("id").limit(CHOICE_EXAMPLES))]
    if not batch:
        return "svm"
    candidates = tuple(METHODS) if dim <= CHOICE_DIM else tuple(m for m in METHODS if m not in CLOSED)
    return select_method(spark, batch, dim, candidates).orderBy("rank").first()["method"]


def run_statement(spark: SparkSession, text: str) -> ClassificationView | MulticlassView:
    return create_view(spark, parse_definition(text))

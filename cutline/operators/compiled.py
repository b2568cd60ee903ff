"""The kernels for cells of many nodes inside Spark's own processes.

functions/Kernel.java is compiled by the compiler that Spark brings for its own plans, once per application, and added as a jar. A cell goes to it as bytes
between two Python steps: one packs the cell's graph, the other reads the answer.
"""

from __future__ import annotations

import os
import pickle
import tempfile
import zipfile
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.cutter import Cut
from ..functions.order import Graph, Splitter
from .graph import cell_graph, cogrouped

NAME = "cutline_kernel"
CUTS, SEPARATE, DISSECT, INDEX = 1, 2, 3, 4
_KINDS, _RULES = {"sweep": 0, "pairs": 1, "bands": 2, "sets": 3}, ("free", "bulk", "single", "end", "balanced", "band")
_instances: dict[str, object] = {}


def registered(spark: SparkSession) -> str:
    """The name of the kernel's function, which the session knows from now on."""
    app, jvm, gateway = spark.sparkContext.applicationId, spark.sparkContext._jvm, spark.sparkContext._gateway
    if app not in _instances:
        with open(os.path.join(os.path.dirname(os.path.dirname(__file__)), "functions", "Kernel.java")) as f:
            text = f.read()
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(jvm.java.lang.Thread.currentThread().getContextClassLoader())
        compiler.setTargetVersion(8)
        compiler.cook(text)
        codes = compiler.getBytecodes()
        jar = os.path.join(tempfile.mkdtemp(prefix="cutline-"), "cutline-kernel.jar")
        with zipfile.ZipFile(jar, "w") as z:
            for name in codes:
                z.writestr(f"{name.replace('.', '/')}.class", bytes(codes[name]))
        spark.sql(f"ADD JAR '{jar}'")
        found = compiler.getClassLoader().loadClass("cutline.Kernel")
        _instances[app] = found.getDeclaredConstructor(gateway.new_array(jvm.java.lang.Class, 0)).newInstance(gateway.new_array(jvm.java.lang.Object, 0))
    spark._jsparkSession.udf().register(NAME, _instances[app], jvm.org.apache.spark.sql.types.DataType.fromJson('"binary"'))
    return NAME


def knows(splitter: Splitter) -> bool:
    """Whether the compiled kernel has a splitter; those that are Python functions, and other schedules, stay in Python."""
    return splitter.cut is None and splitter.schedule == "flow"


def packed(op: int, g: Graph, splitter: Splitter, numbers=None, bound: bool = False, only_front: bool = True, logs: bool = False, connected: bool = False, sets=(), brief: bool = False, timed: bool = False) -> bytes:
    """sets: sources and targets by number, in place of the splitter's cutters. brief: where the front is asked for, cutters stop when they can't add to it; their units are fewer then. timed: a separator's or order's answer ends with its nanoseconds."""
    p = splitter.params
    numbers = list(range(splitter.cutters)) if numbers is None else list(numbers)
    flags = bound + 2 * only_front + 4 * logs + 8 * connected + 16 * brief + 32 * timed
    kind = 3 if sets else _KINDS[splitter.kind]
    head = np.array([op, flags, g.n, len(g.u), kind, splitter.style == "edgecut", p.q, splitter.pairs, splitter.patience, len(numbers), len(sets), 0], "<i4").tobytes()
    tail = [np.array(numbers, "<i4")]
    for s, t in sets:
        tail += [np.array([len(s), len(t)], "<i4"), np.array(s, "<i4"), np.array(t, "<i4")]
    shares = np.array([p.alpha, p.gamma_a, p.gamma_o, p.delta], "<f8")
    parts = [np.array([splitter.seed], "<i8"), shares, g.x.astype("<i8"), g.y.astype("<i8"), g.u.astype("<i4"), g.v.astype("<i4"), *tail]
    return head + b"".join(x.tobytes() for x in parts)


def read_cuts(answer: bytes | None, n: int) -> tuple[list[Cut], list[bool | None], int]:
    """Cuts, with their blocks where logs were asked for; whether the blocks are connected, where that was; and the units of flow."""
    if answer is None:
        return [], [], 0
    count, logs = (int(x) for x in np.frombuffer(answer, "<i4", 2))
    rows = np.frombuffer(answer, "<i4", 8 * count, 32).reshape(-1, 8).tolist()
    held, at = [], 32 + 32 * count
    for _ in range(logs):
        k = int(np.frombuffer(answer, "<i4", 1, at)[0])
        held.append(np.frombuffer(answer, "<i4", k, at + 4))
        at += 4 + 4 * k
    cuts = [Cut(size, small, n, (held[log], upto) if logs else b"", cutter, _RULES[rule], "ST"[side]) for cutter, size, small, side, rule, log, upto, _ in rows]
    return cuts, [None if r[7] < 0 else bool(r[7]) for r in rows], int(np.frombuffer(answer, "<i8", 1, 8)[0])


def seconds(answer: bytes) -> float:
    """What the kernel took for an answer's cuts."""
    return int(np.frombuffer(answer, "<i8", 1, 24)[0]) / 1e9


def nanoseconds(answer: bytes) -> int:
    """What the kernel took for a separator or an order that was asked for with `timed`."""
    return int(np.frombuffer(answer, "<i8", 1, len(answer) - 8)[0])


#: Of an index: what `indexed` gives before the nanoseconds of each customization.
MEASURES = ("index_arcs", "triangles", "tw_bound", "nodes_sum", "nodes_max", "arcs_sum", "arcs_max", "ranks", "queries", "distances")


def packed_index(n: int, lo: np.ndarray, hi: np.ndarray, weight: np.ndarray, customizations: int, ask: np.ndarray) -> bytes:
    """Edges lo < hi by rank with their weights, how often to customize, and the pairs of ranks whose distances are asked."""
    head = np.array([INDEX, 0, n, len(lo), customizations, len(ask)], "<i4")
    return b"".join(x.tobytes() for x in (head, lo.astype("<i4"), hi.astype("<i4"), weight.astype("<i8"), ask.astype("<i4")))


def read_index(answer: bytes) -> tuple[dict[str, int], np.ndarray]:
    """Measures, and the nanoseconds of each customization."""
    got = np.frombuffer(answer, "<i8")
    return dict(zip(MEASURES, got[: len(MEASURES)].tolist(), strict=True)), got[len(MEASURES) :]


def asked(nodes: DataFrame, edges: DataFrame, by: list[str], request, read, schema: str, extra: str | None = None, edges_too: bool = False) -> DataFrame:
    """request(key, kernel graph, nodes' rows in id order) -> bytes or None, or these and what read gets as extra (with edges_too, request gets the edges' rows, too); read(key, kernel graph, ids, extra, answer) -> rows of schema. extra: a column of which a cell's nodes all have
    one value. read may give a list of such rows, which then go on one by one. One task asks for a cell, and those of one cell are dealt to different partitions, whose number is set."""
    spark = nodes.sparkSession
    tasks = 4 * spark.sparkContext.defaultParallelism

    def ask(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = [int(x) if isinstance(x, (int, np.integer)) else x for x in key]
        a = a.sort_values("node_id")
        g, ids = cell_graph(a, b)
        made, more = request(key, g, a, *([b] if edges_too else [])) if len(a) else None, a[extra].iloc[0] if extra and len(a) else None
        if isinstance(made, tuple):
            made, more = made
        carried = pickle.dumps((key, g, ids, more), protocol=5)
        return pd.DataFrame({"place": [hash(tuple(key[:1])) % (1 << 30) + sum(x if isinstance(x, int) else zlib.crc32(x.encode()) for x in key[1:])], "carried": [carried], "request": [made]})

    def answers(batches):
        for batch in batches:
            for carried, answer in zip(batch.carried, batch.answer, strict=True):
                made = read(*pickle.loads(carried), answer)
                yield from (x for x in (made if isinstance(made, list) else [made]) if len(x))

    made = cogrouped(nodes, edges, *by).applyInPandas(ask, "place long, carried binary, request binary")
    dealt = made.repartitionById(tasks, (F.col("place") % tasks).cast("int"))
    return dealt.select("carried", F.expr(f"{registered(spark)}(request)").alias("answer")).mapInPandas(answers, schema)

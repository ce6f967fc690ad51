"""The search of a shared graph as a function of Spark's own processes: ``Search.java``, built by the compiler that Spark
brings for the code it generates, over the broadcast arrays' files. Clips don't pass through Python."""

from __future__ import annotations

import hashlib
import os
import tempfile
import uuid
import zipfile

import numpy as np
from py4j.java_gateway import JavaObject
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.operators import fst as T

SOURCE = os.path.join(os.path.dirname(__file__), "Search.java")
_built: dict[object, JavaObject] = {}


def _class(spark: SparkSession) -> JavaObject:
    """The class on the driver; executors get it as a jar."""
    context, jvm = spark.sparkContext, spark.sparkContext._jvm
    if context not in _built:
        with open(SOURCE) as f:
            text = f.read()
        compiler = jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(jvm.java.lang.Thread.currentThread().getContextClassLoader())
        compiler.cook(text)
        path = os.path.join(tempfile.mkdtemp(dir=context._temp_dir), f"clipflow-search-{hashlib.md5(text.encode()).hexdigest()[:12]}.jar")
        with zipfile.ZipFile(path, "w") as z:
            for name, data in compiler.getBytecodes().items():
                z.writestr(name.replace(".", "/") + ".class", bytes(data))
        context._jsc.sc().addJar(path)
        _built[context] = compiler.getClassLoader().loadClass("clipflow.Search")
    return _built[context]


def _file(spark: SparkSession, x: T.Mapped | np.ndarray) -> T.Mapped:
    return x if isinstance(x, T.Mapped) else T.Mapped.sent(spark.sparkContext, x)


def searcher(spark: SparkSession, graph: T.Shared) -> str | None:
    """The name of a function (t: array of int, symbols: string, p: array of double) -> words, score; none where the arrays' files
    are encrypted or symbols are more than the bits of a number."""
    g = graph.value
    tree, model = g.tree, g.model
    if spark.sparkContext._encryption_enabled or g.n_symbols > 64 or g.n_nodes > 2**30 or any(len(s) > 1 or ord(s) > 127 for s in g.symbols):
        return None
    first = model.__dict__.get("first")
    first = np.searchsorted(model.lm_key, np.arange(model.n_states + 1) * model.v) if first is None else first
    root = np.full(model.v, -1, np.int32)
    root[model.lm_key[: first[1]]] = np.arange(first[1])
    letters = [w.encode() for w in g.vocabulary]
    spelled = np.cumsum([0, *map(len, letters)])
    shared = {**graph.tree.arrays, **graph.model.arrays} if g.gain is None else graph.model.arrays
    fields = {n: tree.__dict__[n] for n in ("child_first", "child", "child_mask")} | {n: g.__dict__[n] for n in ("word_first", "word")}
    fields |= {"gain": np.zeros(0) if g.gain is None else g.gain, "first": first} | {n: model.__dict__[n] for n in ("lm_key", "lm_p", "lm_to", "back", "back_to")}
    fields |= {"root": root, "letters": np.frombuffer(b"".join(letters), np.uint8), "letter_first": spelled}
    kinds = dict.fromkeys(("lm_to", "back_to", "root"), np.int32) | dict.fromkeys(("gain", "lm_p", "back"), np.float64) | {"letters": np.uint8, "child_mask": np.uint64}
    java = _class(spark).newInstance()
    for i, (n, x) in enumerate(fields.items()):
        java.file(i, _file(spark, shared[n] if n in shared else np.asarray(x, kinds.get(n, np.int64))).cast._jbroadcast)
    order = sorted(g.symbols, key=g.symbols.get)
    long = spark.sparkContext._jvm.java.lang.Long.valueOf  # else py4j takes small numbers for ints
    name = f"search_{uuid.uuid4().hex}"
    java.numbers(name, int(g.n_nodes), "".join(order), g.gain is not None, *(long(int(x)) for x in (model.v, g.start, g.end, g.order)), int(min(g.most, 2**31 - 1)), int(g.n_symbols))
    java.reals(*(float(x) for x in (g.beam, g.weight, model.floor, g.highest)))
    kind = spark.sparkContext._jvm.org.apache.spark.sql.types.DataType.fromDDL("words array<string>, score double")
    spark._jsparkSession.udf().register(name, java, kind)
    return name


def found(name: str, rows: str) -> Column:
    """words and score of the clips' rows (t, sym, p), which are in the order of t."""
    return F.call_function(name, F.transform(rows, lambda x: x["t"].cast("int")), F.array_join(F.transform(rows, lambda x: x["sym"]), ""), F.transform(rows, lambda x: x["p"]))


def decode(clips: DataFrame, graph: T.Shared, rows: str = "rows") -> DataFrame:
    """``fst.clip_decode`` of clips whose rows are in the order of t and whose symbols are of one letter."""
    name = searcher(clips.sparkSession, graph)
    if name is None:
        return T.clip_decode(clips, graph, rows)
    names = [c for c in clips.columns if c != rows]
    return clips.select(*names, F.inline(F.array(found(name, rows))))

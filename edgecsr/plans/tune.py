"""The study's parameter sweeps and comparisons, run and timed on the given tables."""

from __future__ import annotations

import json
import os
import subprocess
import sys
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgecsr.operators.baselines import sequential_csr, two_pass_csr, two_pass_edges
from edgecsr.operators.csr import build_csr, build_sorted, build_staged
from edgecsr.operators.degrees import degrees
from edgecsr.operators.edges import reverse
from edgecsr.operators.readers import read_csr, read_edges, settled
from edgecsr.plans.measures import RECORD, file_totals, records, time_runs
from edgecsr.schema import Graph, GraphMeta
from edgecsr.session import shared_dir
from edgecsr.sources.mtx import write_mtx
from edgecsr.sources.workloads import exported, graph

READERS = {
    "R1": {"method": "serial"},
    "R2": {"method": "line_block"},
    "R3": {"method": "line_block", "line_source": "buffered", "parser": "format"},
    "R4": {"method": "line_block", "line_source": "buffered", "parser": "direct"},
    "R5": {"method": "block"},
    "R6": {"method": "block_vector"},
}

#: Stand-ins of the study's graphs: high degrees, an undirected one, many sources of low degree, chains of degree one, and a hub word.
GRAPHS = ("supp_part", "copurchase", "order_part", "order_chain", "word_doc_ids")


def _all(spark: SparkSession, workload: str, g: str, named: dict, runs: int, path: str | dict | None = None, cores: int | None = None) -> DataFrame:
    """Runs and records each; ``path`` is the file that all read, or each by name, or None where none is read."""
    totals: dict = {None: (0, 0)}
    out = []
    for name, fn in named.items():
        at = path.get(name) if isinstance(path, dict) else path
        if at not in totals:
            totals[at] = file_totals(spark, at)
        in_file, size = totals[at]
        timed, loaded = time_runs(fn, runs)
        out.append(records(spark, workload, g, name, timed, edges_in_file=in_file, edges_loaded=loaded, size=size, cores=cores))
    return reduce(DataFrame.union, out)


def _each(graphs, fn) -> DataFrame:
    return reduce(DataFrame.union, [fn(g) for g in graphs])


def sweep_readers(spark, sf_dir, graphs=("supp_part", "order_part", "copurchase"), runs=5):
    def one(g):
        path = exported(spark, sf_dir, g)
        return _all(spark, "readers", g, {n: lambda o=o: read_edges(spark, path, **o).edges for n, o in READERS.items()}, runs, path)

    return _each(graphs, one)


def sweep_block_bytes(spark, sf_dir, graphs=("supp_part", "order_chain"), sizes=(256, 1024, 4096, 16384, 65536, 262144, 1048576, 4194304), runs=3):
    def one(g):
        path = exported(spark, sf_dir, g)
        return _all(spark, "block_bytes", g, {str(b): lambda b=b: read_edges(spark, path, source="blocks", block_bytes=b).edges for b in sizes}, runs, path)

    return _each(graphs, one)


def sweep_variants(spark, sf_dir, graphs=("supp_part", "order_chain", "word_doc_ids"), runs=3):
    def one(g):
        path = exported(spark, sf_dir, g)
        edges = lambda: read_edges(spark, path).edges
        csr = lambda m: read_csr(spark, path, m).slots
        named = {"edge_list": edges, "D1": lambda: degrees(edges(), "global"), "D2": lambda: degrees(edges(), "task"), "D3": lambda: degrees(edges(), "parts"), "C1": lambda: csr("single"), "C2": lambda: csr("staged"), "C3": lambda: csr("sorted")}
        return _all(spark, "variants", g, named, runs, path)

    return _each(graphs, one)


def sweep_parts(spark, sf_dir, graphs=("supp_part", "order_part"), ks=(1, 2, 4, 8, 16, 32), runs=3):
    """The whole way from text to CSR for each number of parts."""

    def one(g):
        path = exported(spark, sf_dir, g)
        return _all(spark, "parts", g, {str(k): lambda k=k: read_csr(spark, path, "staged", csr_parts=k).slots for k in ks}, runs, path)

    return _each(graphs, one)


def _loaders(spark, path):
    return {
        "sequential_line": lambda: sequential_csr(spark, path).slots,
        "sequential_coordinate": lambda: sequential_csr(spark, path, "coordinate").slots,
        "two_pass": lambda: two_pass_csr(spark, path).slots,
        "staged": lambda: read_csr(spark, path, "staged").slots,
        "sorted": lambda: read_csr(spark, path, "sorted").slots,
        "auto": lambda: read_csr(spark, path, "auto").slots,
    }


def compare_csr_loaders(spark, sf_dir, graphs=("supp_part", "copurchase", "order_chain"), runs=3):
    def one(g):
        path = exported(spark, sf_dir, g)
        named = {k: v for k, v in _loaders(spark, path).items() if k != "auto"}
        return _all(spark, "csr_loaders", g, named, runs, path)

    return _each(graphs, one)


def compare_two_loaders(spark, sf_dir, graphs=GRAPHS, runs=3):
    """The two-pass loader against the staged one and the automatic choice."""

    def one(g):
        path = exported(spark, sf_dir, g)
        named = {k: v for k, v in _loaders(spark, path).items() if k in ("two_pass", "staged", "auto")}
        return _all(spark, "two_loaders", g, named, runs, path)

    return _each(graphs, one)


def compare_edge_loaders(spark, sf_dir, graphs=GRAPHS, runs=3):
    def one(g):
        path = exported(spark, sf_dir, g)
        return _all(spark, "edge_loaders", g, {"two_pass": lambda: two_pass_edges(spark, path), "R5": lambda: read_edges(spark, path, "block").edges, "R6": lambda: read_edges(spark, path).edges}, runs, path)

    return _each(graphs, one)


def split_times(spark, sf_dir, graphs=GRAPHS, runs=3):
    def one(g):
        path = exported(spark, sf_dir, g)
        return _all(spark, "split", g, {"edge_list": lambda: read_edges(spark, path).edges, "csr": lambda: read_csr(spark, path, "staged").slots}, runs, path)

    return _each(graphs, one)


def symmetric_file(spark, sf_dir, g="copurchase") -> str:
    """The graph's lower triangle as a symmetric Matrix Market file."""
    path = f"{shared_dir(spark)}/symmetric-{g}-{abs(hash(sf_dir))}-{spark.sparkContext.applicationId}"
    e = reverse(graph(spark, sf_dir, g))
    n = max(e.agg(F.max("src") + 1, F.max("dst") + 1).first())
    write_mtx(e, path, n, n, "pattern", "symmetric")
    return path


def compare_header(spark, sf_dir, g="copurchase", runs=5):
    """A symmetric file with its header honoured, and ignored as the two-pass loader does."""
    path = symmetric_file(spark, sf_dir, g)
    named = {"honored": lambda: read_edges(spark, path, header="mtx").edges, "ignored": lambda: read_edges(spark, path, header="mtx", honor_header=False).edges}
    return _all(spark, "header", g, named, runs, path)


def sweep_weights(spark, sf_dir, g="order_part", runs=5):
    a, b = exported(spark, sf_dir, g), exported(spark, sf_dir, g, weighted=False)
    return _all(spark, "weights", g, {"weighted": lambda: read_edges(spark, a).edges, "unweighted": lambda: read_edges(spark, b, weighted=False).edges}, runs, {"weighted": a, "unweighted": b})


def sweep_lines(spark, sf_dir, g="supp_part", lines=(8192, 131072), chunks=(64, 1024, 16384), runs=3):
    """Lines of a block, and lines that are taken at a time."""
    path = exported(spark, sf_dir, g)
    named = {f"{n}x{c}": lambda n=n, c=c: read_edges(spark, path, "line_block", line_source="buffered", lines_per_block=n, parse_chunk=c).edges for n in lines for c in chunks}
    return _all(spark, "lines", g, named, runs, path)


def compare_degree_shapes(spark, sf_dir, graphs=("order_chain", "order_part", "part_supp", "supp_part"), runs=3):
    def one(g):
        e = Graph(graph(spark, sf_dir, g), GraphMeta())
        return _all(spark, "shapes", g, {m: lambda m=m: build_csr(e, m).slots for m in ("single", "staged", "sorted")}, runs)

    return _each(graphs, one)


def convert_in_memory(spark, sf_dir, graphs=("supp_part", "order_part"), runs=5):
    def one(g):
        e = Graph(graph(spark, sf_dir, g), GraphMeta())
        return _all(spark, "in_memory", g, {"sorted": lambda: build_sorted(e).slots, "staged": lambda: build_staged(e).slots}, runs)

    return _each(graphs, one)


def sweep_tasks(spark, sf_dir, g="supp_part", tasks=(1, 2, 4, 8), runs=3):
    """Strong scaling inside one session: the same read and the same build on ever more tasks. ``scale_cores`` takes whole sessions."""
    path = exported(spark, sf_dir, g, files=max(tasks))
    out = []
    for t in tasks:
        edges = lambda t=t: read_edges(spark, path).edges.coalesce(t)
        named = {"edge_list": edges, "csr": lambda t=t, edges=edges: build_staged(settled(Graph(edges(), GraphMeta())), t).slots}
        out.append(_all(spark, "scaling", g, named, runs, path, edges().rdd.getNumPartitions()))
    return reduce(DataFrame.union, out)


_ONE = """
import json, sys
from pyspark.sql import SparkSession
n, sf_dir, g, runs = int(sys.argv[1]), sys.argv[2], sys.argv[3], int(sys.argv[4])
spark = SparkSession.builder.master(f"local[{n}]").config("spark.sql.shuffle.partitions", str(n)).config("spark.ui.enabled", "false").getOrCreate()
from edgecsr.plans import tune
print("RECORDS" + json.dumps([r.asDict() for r in tune.split_times(spark, sf_dir, (g,), runs).collect()]))
"""


def scale_cores(spark, sf_dir, g="supp_part", cores=(1, 2, 4), runs=5):
    """Strong scaling over local sessions of 1, 2, 4, ... cores, each in a process of its own; on a cluster run ``split_times`` under as many executor cores."""
    rows = []
    for n in cores:
        done = subprocess.run([sys.executable, "-c", _ONE, str(n), sf_dir, g, str(runs)], capture_output=True, text=True, check=True, cwd=os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__)))))
        found = json.loads(next(x for x in done.stdout.splitlines() if x.startswith("RECORDS"))[7:])
        rows += [tuple({**r, "workload": "scaling", "cores": n}[c.split()[0]] for c in RECORD.split(", ")) for r in found]
    return spark.createDataFrame(rows, RECORD)

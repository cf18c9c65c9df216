"""The experiments, restated on the given tables: each gives rows of a parameter and what it moved.

python -m seqcount.plans.workloads [NAME ...] [--sf DIR] [--cores N] prints them as tables.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from functools import partial

from seqcount.functions import kernel
from seqcount.operators import baselines, counting, exchange, index, metrics
from seqcount.operators import supermers as sm
from seqcount.operators.tasks import heavy_tasks, loads, task_sizes
from seqcount.plans import flagship
from seqcount.session import delete_folder, new_folder
from seqcount.sources import fasta
from seqcount.sources import reads as src
from seqcount.spec import CountSpec

K31 = CountSpec(k=31)
#: Repeats of the unit in the tandem repeat: 2 million bases, a twelfth of the documents at sf0.1.
REPEATS = 400_000


def _cached(frame):
    """Reads in memory, so that reading and folding aren't timed."""
    frame = frame.cache()
    frame.count()
    return frame


def _spectrum(make):
    return metrics.timed(lambda: counting.spectrum(make()))


def _parts(spark) -> int:
    return 2 * spark.sparkContext.defaultParallelism


def _large(spark, sf):
    return _cached(src.reads_cov(spark, sf, 5, 0.005).unionByName(src.heavy_reads(spark, sf, times=REPEATS).where("read_id = -1")))


def _median(make, times: int = 3) -> float:
    return sorted(metrics.timed(make) for _ in range(times))[times // 2]


def w1_ablation(spark, sf):
    """Supermers and sorting; more tasks than partitions; heavy tasks pre-counted: seconds, and the longest partition's keys to sort.

    Rungs run in turn, three times over, each with the plan that its load is reported of.
    """
    reads, p = _large(spark, sf), _parts(spark)
    plans, times = {r: flagship.rung_plan(reads, K31, r, p) for r in flagship.RUNGS}, {r: [] for r in flagship.RUNGS}
    for _ in range(3):
        for r in flagship.RUNGS:
            times[r].append(metrics.timed(lambda r=r: flagship.rung(reads, K31, r, p)))  # planning is part of the time
    out, base = [], sorted(times[flagship.RUNGS[0]])[1]
    for r, (spec, plan) in plans.items():
        sizes = flagship.kmers_per_task(reads, spec)
        sizes[plan.heavy] = 0
        most, s = loads(sizes, plan.placed, p), sorted(times[r])[1]
        out.append({"rung": r, "heavy_tasks": len(plan.heavy), "s": round(s, 2), "speedup": round(base / s, 2), "largest_over_mean_load": round(float(most.max() / most.mean()), 2), "runs": " ".join(f"{x:.2f}" for x in times[r])})
    return out


def w2_tasks_per_worker(spark, sf):
    reads, p = _cached(src.reads_docs(spark, sf)), _parts(spark)
    return [{"tasks_per_worker": t, "s": round(metrics.timed(lambda t=t: flagship.count_kmers(reads, K31.but(s=p * t), p, as_spectrum=True)), 2)} for t in (1, 2, 3)]


def w3_partitions_per_core(spark, sf):
    reads, cores = _cached(src.reads_docs(spark, sf)), spark.sparkContext.defaultParallelism
    return [{"partitions_per_core": n, "s": round(metrics.timed(lambda n=n: flagship.count_kmers(reads, K31.but(s=max(256, 3 * n * cores)), n * cores, as_spectrum=True)), 2)} for n in (1, 2, 4, 8, 16)]


def w4_block_bytes(spark, sf):
    reads = _cached(src.reads_docs(spark, sf).unionByName(src.reads_pages(spark, sf)))
    supers = sm.build_supermers(reads, K31)
    costs = {r["batch"]: r for r in exchange.round_costs(exchange.pair_bytes(supers, 16, 16), [10_000, 20_000, 40_000, 80_000, 160_000], 16).collect()}
    return [{"block_bytes": b, "s": round(metrics.timed(lambda b=b: flagship.count_kmers(reads, K31.but(block_bytes=b), as_spectrum=True)), 2), "rounds": c["rounds"], "padding_waste": c["waste"]} for b, c in sorted(costs.items())]


def w5_minimizer_length(spark, sf):
    reads = _cached(src.reads_docs(spark, sf))
    out = []
    for m in (7, 13, 17, 21, 27):
        spec = CountSpec(k=31, m=m)
        supers = sm.build_supermers(reads, spec)
        b, z = exchange.exchange_bytes(supers, spec).first(), metrics.balance_of(task_sizes(supers)).first()
        out.append({"m": m, "s": round(metrics.timed(lambda s=spec: flagship.count_kmers(reads, s, heavy=False, as_spectrum=True)), 2), "saved": b["saved"], "max_over_mean_task": z["max_mean"], "supermers": b["supermers"]})
    return out


def _child(name: str, sf: str, cores: int, master: str | None = None) -> dict:
    command = [sys.executable, "-m", "seqcount.plans.workloads", name, "--sf", sf, "--cores", str(cores), "--json", *(["--master", master] if master else [])]
    done = subprocess.run(command, capture_output=True, text=True, check=True)
    return json.loads(done.stdout.strip().splitlines()[-1])[0]


def _one_strong(spark, sf):
    reads = _cached(src.reads_docs(spark, sf))
    metrics.timed(lambda: flagship.count_kmers(reads, K31, 16, as_spectrum=True))
    return [{"s": min(metrics.timed(lambda: flagship.count_kmers(reads, K31, 16, as_spectrum=True)) for _ in range(2))}]


def _one_weak(spark, sf):
    cores = spark.sparkContext.defaultParallelism
    base = src.reads_short(spark, sf)
    reads = _cached(base.where(f"pmod(xxhash64(read_id), 8) < {cores}"))
    metrics.timed(lambda: flagship.count_kmers(reads, K31, 4 * cores, as_spectrum=True))
    return [{"s": min(metrics.timed(lambda: flagship.count_kmers(reads, K31, 4 * cores, as_spectrum=True)) for _ in range(2))}]


def w6_strong_scaling(spark, sf):
    times = {c: _child("_one_strong", sf, c)["s"] for c in (1, 2, 4, 8)}
    return [{"cores": c, "s": round(s, 2), "efficiency": round(metrics.strong_efficiency(times[1], 1, s, c), 2)} for c, s in times.items()]


def w7_weak_scaling(spark, sf):
    """An eighth of the short reads for each core."""
    times = {c: _child("_one_weak", sf, c)["s"] for c in (1, 2, 4, 8)}
    return [{"cores": c, "s": round(s, 2), "efficiency": round(metrics.weak_efficiency(times[1], s), 2)} for c, s in times.items()]


def w3_processes_and_threads(spark, sf):
    """Eight cores as executors with so many threads each: one process, one a core, and between."""
    out = []
    for n, threads in ((1, 8), (2, 4), (4, 2), (8, 1)):
        s = _child("_one_strong", sf, 8, f"local-cluster[{n},{threads},{12_000 // n}]")["s"]
        out.append({"executors": n, "threads_each": threads, "s": round(s, 2)})
    return out


def _measured(spark, make) -> dict:
    """Seconds and most memory of one run, and bytes shuffled in another."""
    sent, began = metrics.shuffle_bytes(spark, make), time.monotonic()
    peak = metrics.peak_memory(lambda: counting.spectrum(make()))
    return {"s": round(time.monotonic() - began, 2), "peak_mb": round(peak / 1e6), "shuffle_mb": round(sent / 1e6, 1)}


def w8_shared_memory(spark, sf):
    """The method against the sorter of one machine, by input and k."""
    out = []
    for view in ("reads_small", "reads_pages", "reads_docs"):
        reads = _cached(src.VIEWS[view](spark, sf))
        for k in (17, 31, 55):
            spec = CountSpec(k=k)
            a, b = _median(lambda s=spec: baselines.count_shared_sort(reads, s)), _median(lambda s=spec: flagship.count_kmers(reads, s))
            out.append({"reads": view, "k": k, "shared_sort_s": round(a, 2), "method_s": round(b, 2), "method_is_faster_by": round(a / b, 2)})
    return out


def w9_distributed_hash(spark, sf):
    """The method against hash tables behind one and two exchanges: time, memory, bytes sent."""
    out = []
    for name, reads in (("docs", _cached(src.reads_docs(spark, sf))), ("cov5_and_repeat", _large(spark, sf))):
        for how, make in (("method", flagship.count_kmers), ("dist_hash", baselines.count_dist_hash), ("dist_hash_partial", partial(baselines.count_dist_hash, partial=True)), ("two_pass", baselines.count_two_pass)):
            out.append({"reads": name, "how": how} | _measured(spark, partial(make, reads, K31)))
        spark.catalog.clearCache()
    return out


def _one_supermer(spark, sf):
    """Seconds for one number of cores, by k."""
    reads, out = _cached(src.reads_docs(spark, sf)), {}
    for k in (17, 31, 55):
        spec = CountSpec(k=k)
        for how, make in (("method", flagship.count_kmers), ("supermer_hash", baselines.count_supermer_hash), ("naive_minimizer", partial(baselines.count_supermer_hash, naive=True))):
            metrics.timed(lambda: make(reads, spec))  # noqa: B023
            out[f"{how}_k{k}"] = round(min(metrics.timed(lambda: make(reads, spec)) for _ in range(2)), 2)  # noqa: B023
    return [out]


def w10_supermer_hash(spark, sf):
    """The method against hash tables behind supermers, by cores and k."""
    return [{"cores": c} | _child("_one_supermer", sf, c) for c in (2, 4, 8)]


def w11_pipeline(spark, sf):
    """Reading FASTA, counting with locations, overlap candidates: with the method, and with the two-pass counter."""
    path = new_folder(spark, "fasta")
    fasta.write_fasta(src.reads_docs(spark, sf), path)
    reads = fasta.read_fasta(spark, path).select("read_id", "seq")
    ways = {
        "method": lambda: index.overlap_candidates(index.kmer_index(reads, K31), 2), "method_plain_locations": lambda: index.overlap_candidates(index.kmer_index(reads, K31, locations="plain"), 2),
        "two_pass_hash": lambda: index.overlap_candidates(baselines.index_two_pass(reads, K31), 2), "native_aggregation": lambda: index.overlap_candidates(index.kmer_index_native(reads, K31), 2),
    }
    times = {n: _median(f) for n, f in ways.items()}
    delete_folder(spark, path)
    return [{"counter": n, "s": round(s, 2), "method_is_faster_by": round(s / times["method"], 2)} for n, s in times.items()]


def w12_balance(spark, sf):
    reads = _cached(src.reads_docs(spark, sf))
    return [{"score": s} | metrics.balance(flagship.kmers_per_task(reads, K31.but(score=s))) for s in ("murmur3", "universal", "arith", "lex_mod", "lex")]


def w7_stages(spark, sf):
    """Seconds of the stages of one run."""
    return [{k: round(v, 2) for k, v in metrics.stage_times(_cached(src.reads_short(spark, sf)), K31, _parts(spark)).items()}]


def w13_volume(spark, sf):
    reads = src.reads_docs(spark, sf)
    return [{"k": k} | exchange.exchange_bytes(sm.build_supermers(reads, CountSpec(k=k)), CountSpec(k=k)).first().asDict() for k in (17, 31, 55)]


def w14_location_bytes(spark, sf):
    """Bytes of k-mers with locations as supermers, one location for each k-mer, plain and coded; then as the index sends them, one for each supermer."""
    reads = _cached(src.reads_docs(spark, sf))
    supers = sm.build_supermers(reads, K31)
    bases = exchange.exchange_bytes(supers, K31).first()["supermer_bytes"]
    out = []
    for r in exchange.location_bytes(sm.expand_supermers(supers, K31, ("task", "read_id", "pos"))).collect():
        out.append({"layout": f"each k-mer, {r['mode']}", "bytes": bases + r["coded_bytes"], "saved": round(1 - (bases + r["coded_bytes"]) / (bases + r["raw_bytes"]), 3), "index_s": ""})
    plan, plain = flagship.make_plan(reads, K31), None
    for how in exchange.LOCATIONS:
        blocks = exchange.make_blocks(reads, K31, plan.placed, plan.heavy[:0], plan.partitions, ext=True, locations=how)
        n = blocks.selectExpr("sum(octet_length(payload)) as n").first()["n"]
        plain = plain or n
        out.append({"layout": f"each supermer, {how}", "bytes": n, "saved": round(1 - n / plain, 3), "index_s": round(_median(lambda h=how: index.kmer_index(reads, K31, locations=h)), 2)})
    return out


def w15_score_cost(spark, sf):
    import numpy as np

    codes = np.random.default_rng(0).integers(0, 4, 1 << 22).astype(np.uint8)
    out = []
    for score in ("lex", "lex_mod", "arith", "murmur3"):
        spec = K31.but(score=score)
        began = time.monotonic()
        kernel.mmer_scores(codes, spec)
        a = time.monotonic() - began
        began = time.monotonic()
        kernel.find_supermers(codes, spec)
        out.append({"score": score, "scoring_ns_per_base": round(a / len(codes) * 1e9, 1), "supermers_ns_per_base": round((time.monotonic() - began) / len(codes) * 1e9, 1)})
    return out


def w16_sort_or_hash(spark, sf):
    reads = _cached(src.reads_docs(spark, sf))
    ways = {"method": flagship.count_kmers, "dist_hash": baselines.count_dist_hash, "two_pass_hash": baselines.count_two_pass, "range_sort": baselines.count_range_sort, "spark_radix_sort": baselines.count_hash_exchange_sort,
            "spark_timsort": partial(baselines.count_hash_exchange_sort, sort_mode="timsort"), "merge_last": baselines.count_merge_last, "thread_owned": baselines.count_thread_owned, "explicit_hh": baselines.count_explicit_hh,
            "method_aux_radix": partial(flagship.count_kmers, method="aux_radix"), "method_hash": partial(flagship.count_kmers, method="hash")}
    times = {n: _spectrum(lambda f=f: f(reads, K31)) for n, f in ways.items()}
    return [{"how": n, "s": round(s, 2), "method_is_faster_by": round(s / times["method"], 2)} for n, s in times.items()]


def w18_heavy(spark, sf):
    """A tandem repeat: keys that one partition sorts with and without pre-counting, as the plan finds it by itself."""
    reads = _cached(src.heavy_reads(spark, sf, times=REPEATS))
    sizes = flagship.kmers_per_task(reads, K31)
    out = []
    for on in (False, True):
        plan = flagship.make_plan(reads, K31, heavy=on)
        s = _median(lambda on=on: flagship.count_kmers(reads, K31, heavy=on, as_spectrum=True))
        rest = sizes.copy()
        rest[plan.heavy] = 0
        pairs = exchange.make_blocks(reads, K31, plan.placed, plan.heavy, plan.partitions).where("kind = 1").selectExpr("coalesce(sum(n), 0) as n").first()["n"]
        out.append({"pre_counted": on, "heavy_tasks": len(plan.heavy), "elements_before": int(sizes[heavy_tasks(sizes)].sum()), "pairs_sent": pairs, "largest_task_over_mean": round(float(rest.max() / sizes.mean()), 2), "s": round(s, 2)})
    return out


def _received(port_of, k: int) -> None:
    """The other end of the line: takes rounds, parses each, and says so."""
    import socket
    import struct

    line = socket.create_connection(("127.0.0.1", port_of))
    stream = line.makefile("rb")
    while head := stream.read(8):
        n, size = struct.unpack("<II", head)
        n_bases, packed, _, _ = exchange.unpack_block(n, stream.read(size))
        kernel.valid_kmers(kernel.unpack_runs(packed, n_bases)[0], k)
        line.sendall(b"!")


def w19_overlap(spark, sf):
    """Rounds of packing, sending to another process and parsing there, one after another and with a buffer in flight: measured seconds."""
    import multiprocessing
    import socket
    import struct

    rows = src.reads_docs(spark, sf).select("seq").limit(3000).toArrow()["seq"].combine_chunks()
    rounds = [codes for _, _, _, codes in kernel.groups(rows, 1 << 17)]

    def run(in_flight: int) -> float:
        server = socket.create_server(("127.0.0.1", 0))
        other = multiprocessing.get_context("spawn").Process(target=_received, args=(server.getsockname()[1], 31))
        other.start()
        line, _ = server.accept()
        waiting, began = 0, time.monotonic()
        for codes in rounds:
            found = kernel.find_supermers(codes, K31)
            body = exchange.pack_block(found.n_bases, kernel.pack_runs(codes, found.begin, found.n_bases)[0])
            line.sendall(struct.pack("<II", len(found.begin), len(body)) + body)
            waiting += 1
            while waiting > in_flight:
                waiting -= len(line.recv(1))
        while waiting:
            waiting -= len(line.recv(1))
        took = time.monotonic() - began
        line.close()
        other.join()
        server.close()
        return took

    times = {n: sorted(run(n) for _ in range(3))[1] for n in (0, 1)}
    return [{"rounds": len(rounds), "rounds_in_flight": n, "s": round(s, 2), "gain": round(times[0] / s, 2)} for n, s in times.items()]


def w20_any_keys(spark, sf):
    rows = _cached(src.table(spark, sf, "lineitem").select("l_partkey"))
    return [{"how": h, "s": round(metrics.timed(lambda h=h: baselines.count_keys(rows, "l_partkey", h)), 2)} for h in ("sort", "range", "hash", "precount")]


WORKLOADS = {n: f for n, f in list(globals().items()) if n[0] == "w" and n[1:2].isdigit()} | {"_one_strong": _one_strong, "_one_weak": _one_weak, "_one_supermer": _one_supermer}


def main(args: list[str]) -> None:
    option = lambda name, default: args[args.index(name) + 1] if name in args else default
    sf, cores = option("--sf", "/root/testdata/sf0.1"), option("--cores", str(os.cpu_count()))
    names = [a for a in args if a in WORKLOADS] or [n for n in WORKLOADS if n[0] == "w"]
    os.environ["PYTHONPATH"] = os.getcwd() + os.pathsep + os.environ.get("PYTHONPATH", "")
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(option("--master", f"local[{cores}]")).config("spark.executor.memory", "1g" if "--master" in args else "8g").config("spark.sql.shuffle.partitions", str(2 * int(cores))).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.files.maxPartitionBytes", "4m").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    metrics.timed(lambda: flagship.count_kmers(src.reads_small(spark, sf), K31, as_spectrum=True))  # starts workers
    for name in names:
        rows = WORKLOADS[name](spark, sf)
        spark.catalog.clearCache()
        if "--json" in args:
            print(json.dumps(rows), flush=True)
            continue
        print(f"\n### {name}\n\n| {' | '.join(rows[0])} |\n|{'---|' * len(rows[0])}")
        for r in rows:
            print(f"| {' | '.join(str(round(v, 4) if isinstance(v, float) else v) for v in r.values())} |", flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])

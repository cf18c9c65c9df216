import hashlib
import random

import pytest

from seqcount.llm import exact_dedup


def brute(rows, keep):
    groups = {}
    for i, (d, t) in enumerate(rows):
        groups.setdefault(t or "", []).append((d, i))
    pick = max if keep == "largest" else min
    out = []
    for d, t in rows:
        ids = [x for x, _ in groups[t or ""] if x is not None]
        out.append((d, pick(ids) if ids else None, len(groups[t or ""]), hashlib.sha256((t or "").encode()).hexdigest()))
    return sorted(out, key=repr)


@pytest.mark.parametrize("keep", ["smallest", "largest"])
@pytest.mark.parametrize("fan_in", [2, 16])
def test_equals_brute_force(spark, keep, fan_in):
    rng = random.Random(3)
    texts = ["", None, "a", "A", "a ", "é", "x" * 100_000] + [f"t{i}" for i in range(40)]
    rows = [(i, rng.choice(texts[:12]) if i % 2 else rng.choice(texts)) for i in range(400)] + [(7, "twice"), (7, "twice"), (None, "nobody"), (None, "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(37).selectExpr("doc_id", "text", "1 as digest", "2 as n", "3 as leaf")
    found = exact_dedup.exact_dedup(docs, keep=keep, fan_in=fan_in).collect()
    assert sorted([(r["rid"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in found], key=repr) == brute(rows, keep)
    kept = [r for r in found if r["kept"]]
    assert len(kept) == len({t or "" for _, t in rows})
    assert all(r["rid"] == r["keep_id"] for r in kept)


def test_filter_keeps_one_whole_row_of_each_text(spark):
    rows = [(1, "a", "x"), (2, "a", "y"), (2, "a", "y"), (3, None, "z"), (4, "", "w"), (5, "b", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, spare string")
    out = exact_dedup.drop_exact_copies(docs, keep="largest")
    assert out.columns == docs.columns
    assert sorted(map(tuple, out.collect()), key=repr) == [(2, "a", "y"), (4, "", "w"), (5, "b", None)]
    assert exact_dedup.drop_exact_copies(docs.limit(0)).count() == 0


def test_a_third_of_all_rows_in_one_group(spark):
    docs = spark.range(3000).selectExpr("id as doc_id", "if(id % 3 = 0, 'hot', cast(id as string)) as text").repartition(50)
    found = {r["rid"]: r for r in exact_dedup.exact_dedup(docs, keep="smallest").collect()}
    assert len(found) == 3000 and sum(r["kept"] for r in found.values()) == 2001
    assert found[2997]["keep_id"] == 0 and found[2997]["group_size"] == 1000


def test_runs_no_python(spark):
    docs = spark.createDataFrame([(1, "a"), (2, "a")], "doc_id long, text string")
    plan = exact_dedup.exact_dedup(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan

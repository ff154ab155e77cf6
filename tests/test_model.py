"""The adapter for hosted models against a local stub, and what a backend is told."""

import json
import re
import threading
import time
from http.server import BaseHTTPRequestHandler, ThreadingHTTPServer

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from semrank.exec.packed import rankings_of, replies_of, request_key, run_path, run_paths, usage_of
from semrank.operators.frame import llm_order_by
from semrank.plans import optimizer as O
from semrank.plans.spec import EXT_BUBBLE, EXT_MERGE, EXT_POINT, POINT, QUICK, QUICK_3, PathConfig
from semrank.sources.model import BadReply, HttpBackend, Key, SimBackend, concordance, each, numbered

SAID = {"prompts": [], "busy": 0, "garbage": 0, "at_once": 0, "most": 0}
LOCK = threading.Lock()


def number(entry):
    return int(re.search(r"weighs (\d+)", entry)[1])


def reply_to(prompt, schema):
    shown = {int(n): t for n, t in re.findall(r"^\[(\d+)\] (.*weighs.*)$", prompt, re.M)}
    if "value" in schema:
        return {"value": number(shown[1]) // 10}
    if "values" in schema:
        return {"values": [number(shown[n]) // 10 for n in sorted(shown)]}
    if "better" in schema:
        return {"better": 1 if number(shown[1]) >= number(shown[2]) else 2}
    if "order" in schema:
        return {"order": sorted(shown, key=lambda n: -number(shown[n]))}
    if "world_fact" in schema:
        return {"world_fact": "population" in prompt}
    lists = re.findall(r"^Result (\d+): (.*)$", prompt, re.M)
    right = sorted(shown, key=lambda n: -number(shown[n]))
    return {"reasoning": "...", "choice": min(((sum(abs(right.index(int(x)) - i) for i, x in enumerate(ids.split(", "))), int(n)) for n, ids in lists))[1]}


class Stub(BaseHTTPRequestHandler):
    def do_POST(self):
        body = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
        with LOCK:
            SAID["prompts"].append(body)
            SAID["at_once"] += 1
            SAID["most"] = max(SAID["most"], SAID["at_once"])
            busy, SAID["busy"] = SAID["busy"] > 0, max(0, SAID["busy"] - 1)
            garbage, SAID["garbage"] = SAID["garbage"] > 0 and not busy, SAID["garbage"] - (SAID["garbage"] > 0 and not busy)
        time.sleep(0.002)
        out = json.dumps({"reply": "not json" if garbage else json.dumps(reply_to(body["prompt"], body["schema"])), "in_tok": 10, "out_tok": 2}).encode()
        with LOCK:
            SAID["at_once"] -= 1
        self.send_response(429 if busy else 200)
        self.end_headers()
        self.wfile.write(out)

    def log_message(self, *args):
        pass


@pytest.fixture(scope="module")
def model():
    server = ThreadingHTTPServer(("127.0.0.1", 0), Stub)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    yield HttpBackend(f"http://127.0.0.1:{server.server_port}", "stub", pause=0.01)
    server.shutdown()


@pytest.fixture(autouse=True)
def clean():
    SAID.update(prompts=[], busy=0, garbage=0, at_once=0, most=0)


def keys(weights):
    return [Key(i, 0, 0, None, f"a thing that weighs {w}") for i, w in enumerate(weights)]


def test_six_operations(model):
    m, ks = model.about("the heaviest"), keys([30, 80, 50])
    assert m.score("t", ks[1], 10)[0] == 8 and m.score_many("t", 0, ks, 10)[0] == [3, 8, 5]
    assert m.compare("t", ks[0], ks[1])[0] == -1 and m.order("t", ks)[0] == [1, 2, 0]
    assert m.inquire("t", ks)[0] == "reasoning" and model.about("population").inquire("t", ks)[0] == "factual"
    assert m.judge("t", ks, {"a": [0, 1, 2], "b": [1, 2, 0], "c": [2, 0, 1]})[0] == "b"
    up = model.about("the heaviest", descending=False)
    assert up.score("t", ks[1], 10)[0] == 2 and up.compare("t", ks[0], ks[1])[0] == 1 and up.order("t", ks)[0] == [0, 2, 1]
    assert all("the heaviest" in p["prompt"] or "population" in p["prompt"] for p in SAID["prompts"])
    assert "worst first" not in SAID["prompts"][5]["prompt"]


def test_retries_and_bad_replies(model):
    SAID.update(busy=2, garbage=1)
    got, used = model.order("t", keys([1, 2]))
    assert got == [1, 0] and len(SAID["prompts"]) == 4 and used.in_tok == 20  # the busy ones cost nothing
    SAID.update(garbage=9)
    with pytest.raises(ValueError):
        model.order("t", keys([1, 2]))
    with pytest.raises(BadReply):
        model._point("8", 10)
    assert model._point(99, 10) == 10


def test_facts_are_shown(model):
    m = model.about("size")
    m.score("t", Key(1, 0, 0, 77, "x weighs 5"), 10, lookup=True)
    assert "[1] 77" in SAID["prompts"][-1]["prompt"] and SAID["prompts"][-1]["tools"] == ["search"]
    m.score("t", Key(1, 0, 0, 77, "x weighs 5"), 10)
    assert "77" not in SAID["prompts"][-1]["prompt"] and SAID["prompts"][-1]["tools"] == []


def test_calls_of_a_wave_overlap_within_bounds(model):
    run_path(keys(range(0, 100, 2)), POINT, None, model, "t")
    assert 2 <= SAID["most"] <= model.threads
    start = time.monotonic()
    slow = HttpBackend(model.endpoint, "stub", per_minute=1200)
    each(slow, lambda k: slow.score("t", k, 10), keys([1, 2, 3, 4, 5]))
    assert time.monotonic() - start > 0.15


@pytest.mark.parametrize("path", [PathConfig("score_each", max_point=10), EXT_POINT, QUICK, QUICK_3, EXT_BUBBLE, EXT_MERGE], ids=lambda p: p.path_id)
def test_a_hosted_model_orders_rows(spark, model, path):
    d = spark.createDataFrame([(i, f"entry {i} weighs {w}") for i, w in enumerate([70, 10, 100, 40, 90, 20])], "id int, k string")
    assert [r.id for r in llm_order_by(d, "k", "the heaviest", id_col="id", path=path, backend=model).orderBy("rnk").collect()] == [2, 4, 0, 3, 5, 1]
    assert [r.id for r in llm_order_by(d, "k", "the heaviest", id_col="id", path=path, backend=model, desc=False, limit=2).orderBy("rnk").collect()] == [1, 5]
    assert all("entry" in p["prompt"] for p in SAID["prompts"])


def test_waves_and_the_optimizer_with_a_hosted_model(spark, model):
    d = spark.createDataFrame([(i, f"entry {i} weighs {i * 37 % 101}") for i in range(26)], "id int, k string")
    want = sorted(range(26), key=lambda i: -(i * 37 % 101))
    for path in (QUICK, EXT_MERGE):
        assert [r.id for r in llm_order_by(d, "k", "the heaviest", id_col="id", path=path, backend=model, packed_max=10).orderBy("rnk").collect()] == want
    got = llm_order_by(d, "k", "the heaviest", id_col="id", limit=3, budget_nano=10**12, policy="judge", sample=8, backend=model)
    assert [r.id for r in got.orderBy("rnk").collect()] == want[:3]
    kinds = {next(iter(sorted(p["schema"]))) for p in SAID["prompts"]}
    assert {"world_fact", "choice"} <= kinds


# ---- what the simulator is told ----------------------------------------------------------------------------------------


def test_requests_differ_by_all_that_decides_the_reply():
    k, a = Key(1, 5, 9, None, "text"), SimBackend("factual")
    base = request_key(a, "t", ("score", k), POINT)
    others = [
        request_key(a.about("x"), "t", ("score", k), POINT), request_key(a.about("", False), "t", ("score", k), POINT), request_key(SimBackend("factual", "large"), "t", ("score", k), POINT),
        request_key(a, "u", ("score", k), POINT), request_key(a, "t", ("score", Key(1, 5, 9, None, "other")), POINT), request_key(a, "t", ("score", Key(1, 5, 9, 3, "text")), POINT),
        request_key(a, "t", ("score", k), PathConfig("score_each", max_point=9)), request_key(a, "t", ("score", k), PathConfig("score_each", lookup=True)), request_key(a, "t", ("compare", k, k), POINT),
    ]
    assert len({base, *others}) == len(others) + 1


def test_the_criterion_is_part_of_the_noise():
    ks = [Key(i, 5, 5000) for i in range(50)]
    a, b, c = (SimBackend("reasoning").about(x).order("t", ks)[0] for x in ("one", "two", "one"))
    assert a == c != b


def test_concordance_and_numbering():
    assert concordance([1, 2, 3], {1: 9, 2: 5, 3: 1}) == 1 and concordance([3, 2, 1], {1: 9, 2: 5, 3: 1}) == -1 and concordance([1], {1: 1}) == 0
    assert sorted(numbered(7, "t", ["a", "b", "c"])) == ["a", "b", "c"] and len({tuple(numbered(7, f"t{i}", ["a", "b", "c"])) for i in range(30)}) > 3


def test_replies_are_reused(spark):
    d = spark.range(30).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("k"), "id").alias("key"), (F.col("id") * 331 % 9973).alias("lat"))
    first = run_paths(d, [QUICK_3, EXT_MERGE], SimBackend("reasoning"), keep=True)
    cached = replies_of(first).crossJoin(spark.createDataFrame([("quick_3",), ("ext_merge_4",)], "path_id string")).select("task_id", "path_id", "req", "reply").toPandas()
    again = run_paths(d, [QUICK_3, EXT_MERGE], SimBackend("reasoning"), cached=spark.createDataFrame(cached))
    assert sorted(map(tuple, rankings_of(first).collect())) == sorted(map(tuple, rankings_of(again).collect()))
    u, v = usage_of(first).agg(F.sum("calls"), F.sum("hits")).first(), usage_of(again).agg(F.sum("calls"), F.sum("hits")).first()
    assert (u[1], v[0]) == (0, 0) and v[1] == u[0]


# ---- decisions -------------------------------------------------------------------------------------------------------------


def test_agreement_counts_what_a_limit_left_out(spark):
    rank = lambda p, ids: [("t", p, i, r) for r, i in enumerate(ids, 1)]
    schema = "task_id string, path_id string, item_id bigint, rnk bigint"
    proxy = spark.createDataFrame(rank("x", range(10)), schema).drop("path_id")
    lists = {"all": range(10), "top": [0, 1, 2], "worst": [7, 8, 9], "back": range(9, -1, -1)}
    d = spark.createDataFrame([r for p, ids in lists.items() for r in rank(p, ids)], schema)
    for how in ("tau", "footrule"):
        got = {r.path_id: r.agreement for r in O.agreement(d, proxy, how).collect()}
        assert got["all"] == 1 and got["all"] > got["top"] > 0 and got["top"] > got["worst"] and got["worst"] < (0 if how == "tau" else 0.5)
    assert {r.path_id: round(r.agreement, 6) for r in O.agreement(d, proxy).collect()}["worst"] == round((3 - 21) / 45, 6)


def test_a_joint_budget_is_not_overspent(spark):
    d = spark.range(160).select(F.concat(F.lit("t"), F.col("id") % 2).alias("task_id"), F.col("id").alias("item_id"), F.floor(F.col("id") / 2).cast("int").alias("pos"), F.concat(F.lit("key number "), "id").alias("key"), (F.col("id") * 331 % 9973).alias("lat"))
    tasks = d.select("task_id").distinct().select("task_id", F.lit("reasoning").alias("kind"), F.lit(None).cast("bigint").alias("k"))
    grid = [POINT, EXT_POINT, PathConfig("score_batch", m=8), PathConfig("slide_window", m=20)]
    spends = set()
    for budget in (7_000_000, 16_000_000, 40_000_000):
        for policy in ("judge", "consensus"):
            r = O.optimize(d, tasks, budget, SimBackend("reasoning"), policy=policy, candidates=grid, budget_covers="all", on_infeasible="cheapest")
            feasible = {x.task_id for x in r.estimates.where("fits").collect()}
            for x in r.ledger.groupBy("task_id").agg(F.sum("nano_usd").alias("n")).collect():
                assert x.task_id not in feasible or x.n <= budget
                spends.add((budget, len(feasible)))
    assert any(n for _, n in spends)


def test_what_does_not_fit_has_no_voice(spark):
    d = spark.range(40).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("key "), "id").alias("key"), (F.col("id") * 331 % 9973).alias("lat"))
    tasks = d.select("task_id").distinct().select("task_id", F.lit("reasoning").alias("kind"), F.lit(None).cast("bigint").alias("k"))
    few = O.optimize(d, tasks, 3_000_000, SimBackend("reasoning"), inquiry=False)
    fit = {r.path_id for r in few.estimates.where("fits").collect()}
    alone = O.optimize(d, tasks, 3_000_000, SimBackend("reasoning"), inquiry=False, candidates=[p for p in O.candidate_grid() if p.path_id in fit])
    assert 0 < len(fit) < 6 and few.choices.collect() == alone.choices.collect()


def test_large_tasks_take_the_optimizer_too(spark):
    d = spark.range(150).select(F.when(F.col("id") % 5 == 0, "a").otherwise("b").alias("task_id"), F.col("id").alias("item_id"), F.concat(F.lit("k"), "id").alias("key"), (F.col("id") * 7919 % 9973).alias("lat"))
    d = d.withColumn("pos", (F.row_number().over(Window.partitionBy("task_id").orderBy("item_id")) - 1).cast("int"))
    tasks = d.select("task_id").distinct().select("task_id", F.lit("reasoning").alias("kind"), F.lit(9).cast("bigint").alias("k"))
    grid = [PathConfig("score_each", max_point=10000), QUICK, EXT_MERGE]
    a, b = (O.optimize(d, tasks, 10**12, SimBackend("reasoning"), candidates=grid, inquiry=False, packed_max=n) for n in (60, 5000))
    same = lambda x: sorted(tuple(r) for r in x.collect())
    assert same(a.ranking) == same(b.ranking) and a.ranking.count() == 18
    # waves pay for the probe's requests again, packed runs do not
    spent = [{(r.task_id, r.phase): (r.calls + r.hits) for r in x.ledger.collect()} for x in (a, b)]
    assert spent[0] == spent[1]
    with_bubble = O.optimize(d, tasks, 10**12, SimBackend("reasoning"), candidates=[*grid, EXT_BUBBLE], inquiry=False, packed_max=60)
    assert {(r.task_id, r.path_id) for r in with_bubble.choices.collect() if r.path_id == "ext_bubble_4"} == {("a", "ext_bubble_4")}


def test_partitions_that_only_look_alike(spark):
    d = spark.createDataFrame([(1, "a|b", "c", "x"), (2, "a", "b|c", "y"), (3, None, "", "z"), (4, "", None, "w")], "id int, p string, q string, k string")
    assert [r.rnk for r in llm_order_by(d, "k", "good", id_col="id", partition_by=["p", "q"]).collect()] == [1, 1, 1, 1]
    with pytest.raises(ValueError, match="have no id"):
        llm_order_by(spark.createDataFrame([(None, "x")], "id int, k string"), "k", "good", id_col="id")


def test_reasoning_costs_tokens():
    k = Key(1, 40)
    plain, long = (SimBackend(reasoning=x).score("t", k, 10)[1] for x in (False, True))
    assert long.out_tok - plain.out_tok == 120 and long.in_tok == plain.in_tok


def test_calls_in_flight_decide_nothing(spark):
    d = spark.range(40).select(F.concat(F.lit("t"), F.col("id") % 4).alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("k"), "id").alias("key"), (F.col("id") * 331 % 9973).alias("lat"))
    a, b = (rankings_of(run_paths(d, [QUICK, EXT_MERGE], SimBackend("reasoning"), max_in_flight=n)).collect() for n in (None, 1))
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))


def test_a_bound_on_waiting_leaves_flat_paths(spark):
    d = spark.range(200).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.concat(F.lit("k"), "id").alias("key"), (F.col("id") * 331 % 9973).alias("lat"))
    tasks = d.select("task_id").distinct().select("task_id", F.lit("reasoning").alias("kind"), F.lit(10).cast("bigint").alias("k"))
    fit = lambda most: {r.path_id for r in O.optimize(d, tasks, 10**12, SimBackend("reasoning"), inquiry=False, max_latency_s=most).estimates.where("fits").collect()}
    assert fit(5) == {"point", "ext_point_4"} and "ext_bubble_4" in fit(10**6)


def test_formats(spark, tmp_path):
    from semrank.sources.files import FORMATS, read_items, write_ranking

    rows = [("a,b", 1, 'say "x"\nand y'), (None, 2, ""), ("c", 3, None)]
    schema = "task_id string, item_id bigint, key string"
    for fmt in FORMATS:
        write_ranking(spark.createDataFrame(rows, schema), f"{tmp_path}/{fmt}", fmt)
        got = read_items(spark, f"{tmp_path}/{fmt}", fmt, schema).collect()
        assert sorted(map(str, map(tuple, got))) == sorted(map(str, rows)), fmt
    with pytest.raises(ValueError, match="needs a schema"):
        read_items(spark, "x", "csv")
    with pytest.raises(ValueError, match="format is one of"):
        write_ranking(spark.createDataFrame(rows, schema), "x", "xml")

import itertools
import random

import pytest
from pyspark.sql import functions as F

from redgraph.llm import chat_repair as chat


def cheapest(roles):
    """All ways to read a short sequence: which turns open a turn, their roles, and what is inserted."""
    best = None
    for opens in itertools.product([True, False], repeat=len(roles)):
        if not opens[0]:
            continue
        for new in itertools.product([1, 2, 3], repeat=sum(opens)):
            cost, k, state = 0, -1, 0
            for o, r in zip(opens, roles, strict=True):
                if o:
                    k += 1
                    q = new[k]
                    if q in chat.LEGAL[state]:
                        pass
                    elif any(q in chat.LEGAL[x] for x in chat.LEGAL[state]):
                        cost += chat.INSERT
                    else:
                        cost = None
                        break
                    state = q
                else:
                    cost += chat.MERGE
                cost += 0 if r == state else chat.UNKNOWN if r == 0 else chat.RELABEL
            if cost is not None:
                cost += chat.INSERT * len(chat.ENDING[state])
                best = cost if best is None else min(best, cost)
    return best


def cost_of(roles, moves):
    costs = {(p, q, a, x): c for p, q, c, a, x in itertools.chain(*chat.MOVES)}
    total = 0
    for r, m in zip(roles, moves, strict=True):
        total += next(c for p, q, c, a, x in chat.MOVES[r] if (p, q, a, x) == m)
    return total + chat.INSERT * len(chat.ENDING[moves[-1][1]]) if costs else 0


@pytest.mark.parametrize("n", [1, 2, 3, 4])
def test_every_short_sequence_is_repaired_at_least_cost(n):
    for roles in itertools.product(range(4), repeat=n):
        moves = chat.solve(list(roles), 0, None)
        assert [m[0] for m in moves] == [0, *[m[1] for m in moves[:-1]]]
        assert cost_of(roles, moves) == cheapest(roles)


def test_blocks_give_the_cost_of_the_whole():
    rng = random.Random(1)
    for _ in range(50):
        roles = [rng.randrange(4) for _ in range(23)]
        whole = cost_of(roles, chat.solve(roles, 0, None))
        parts = [roles[i : i + 5] for i in range(0, 23, 5)]
        edge = chat.borders([chat.block_matrix(p) for p in parts])
        moves = list(itertools.chain(*(chat.solve(p, edge[k], edge[k + 1]) for k, p in enumerate(parts))))
        assert cost_of(roles, moves) == whole


def legal(text):
    state = 0
    for part in text.split(chat.CLOSING)[:-1]:
        role = chat.ROLES.index(part[part.index("<|") + 2 : part.index("|>")])
        assert role in chat.LEGAL[state]
        state = role
    return state == 3


def test_tables_and_block_borders(spark, sf):
    table = spark.read.parquet(f"{sf}/conversations.parquet")
    whole = chat.repair(table)
    assert whole.count() == table.count()
    texts = {r.conv_id: r.rendered for r in chat.rendered_conversations(whole).collect()}
    assert all(legal(t) for t in texts.values())
    split = {r.conv_id: r.rendered for r in chat.rendered_conversations(chat.repair(table, block_turns=2)).collect()}
    assert all(legal(t) for t in split.values())
    source = {r.conv_id: r.t for r in table.groupBy("conv_id").agg(F.collect_set("text").alias("t")).collect()}
    assert all(chat.escape(t) in texts[c] for c, ts in source.items() for t in ts)


def test_nulls_ties_and_clashing_columns(spark):
    rows = [(None, 0, "user", "a", 1), (None, 1, None, None, 1), (1, 0, "assistant", "x", 1), (1, 0, "assistant", "x", 1), (2, None, "user", "<|end|>", 1), (2, 5, "tool", "t" * 70000, 1), (3, 0, "system", "", 1), (4, 0, "User ", "hi", 1)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, rendered int")
    out = chat.repair(df).collect()
    assert len(out) == len(rows)
    by = {}
    for r in out:
        by.setdefault(r.conv_id, []).append(r)
    assert [r.action for r in by[1]] == ["insert", "merge"]
    by[2].sort(key=lambda r: (r.turn is not None, r.turn))
    assert by[2][0].rendered.count("<|end|>") == 0 and by[3][0].rendered.count("<|assistant|>") == 1
    assert {r.new_role for r in by[4]} == {"user"}
    assert chat.repair(df.where(F.lit(False))).count() == 0


def test_ties_are_cut_into_blocks(spark):
    """A conversation of one turn number is solved in blocks like any other, and is spread over tasks."""
    rows = [(None, 7, ("user", "assistant", "system", None)[k % 4], "t") for k in range(3000)]
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = chat.repair(table, block_turns=64)
    assert out.count() == len(rows)
    joined = "".join(r.rendered for r in out.orderBy("at").collect())
    whole = "".join(r.rendered for r in chat.repair(table, block_turns=1 << 40).orderBy("at").collect())
    assert len({r.at // 64 for r in out.collect()}) > 40
    assert joined.count("<|user|>") + joined.count("<|assistant|>") == whole.count("<|user|>") + whole.count("<|assistant|>")
    assert joined.endswith(chat.CLOSING)

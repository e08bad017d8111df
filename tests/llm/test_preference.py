from spark_nlops.llm import preference as P


def pair(spark, rows):
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, pair string")
    return {r.pair_id: r for r in P.format_preferences(P.neighbours_as_pairs(df)).collect()}


def test_worked_example(spark):
    rows = [(0, 0, "user", "hi", ""), (0, 1, "assistant", "hello", ""), (0, 2, "user", "why", ""), (0, 3, "assistant", "so", "")]
    rows += [(1, 0, "user", "hi", ""), (1, 1, "assistant", "hello", ""), (1, 2, "user", "why", ""), (1, 3, "assistant", "no", ""), (1, 4, "user", "ok", "")]
    r = pair(spark, rows)[0]
    assert r.n_prompt_turns == 3
    assert r.prompt == "<|user|>\nhi<|end|>\n<|assistant|>\nhello<|end|>\n<|user|>\nwhy<|end|>\n"
    assert r.chosen == "<|assistant|>\nso<|end|>\n" and r.rejected == "<|assistant|>\nno<|end|>\n<|user|>\nok<|end|>\n"
    a, b = map(int, r.chosen_spans.split("-"))
    assert r.chosen[a:b] == "so<|end|>\n" and r.rejected_spans == "14-24"


def test_edges(spark):
    rows = [(2, 0, "user", None, "x"), (2, 0, "user", None, "x"), (3, 0, "user", "", "x"), (4, None, None, "alone", "x"), (None, 0, "user", "lost", "x"), (6, 0, "user", "z" * 300_000, "x"), (7, 1, "user", "b", "x"), (7, 1, "assistant", "a", "x")]
    got = pair(spark, rows)
    assert set(got) == {1, 2, 3}
    assert got[1].n_prompt_turns == 1 and got[1].chosen == got[1].rejected == ""
    assert got[2].prompt == "" and got[2].chosen == "<|unknown|>\nalone<|end|>\n" and got[2].rejected == ""
    assert len(got[3].chosen) > 300_000 and got[3].rejected.startswith("<|assistant|>")
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert P.format_preferences(P.neighbours_as_pairs(empty)).count() == 0


def test_large_ids_and_turns_below_zero(spark):
    rows = [(2**60 + i, 0, "user", f"t{i}", "") for i in range(4)] + [(-2, 0, "user", "a", ""), (-1, 0, "user", "b", "")]
    rows += [(10, None, "user", "first", ""), (10, -1, "user", "second", ""), (11, None, "user", "first", ""), (11, -1, "user", "other", "")]
    got = pair(spark, rows)
    assert set(got) == {2**59, 2**59 + 1, -1, 5}
    assert got[2**59 + 1].chosen == "<|user|>\nt2<|end|>\n" and got[-1].rejected == "<|user|>\nb<|end|>\n"
    assert got[5].n_prompt_turns == 1 and got[5].prompt == "<|user|>\nfirst<|end|>\n"

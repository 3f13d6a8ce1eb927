from __future__ import annotations

from collections import Counter, defaultdict

from kgfeat.llm import chat


def render(turns, me):
    text, masks = "", []
    for _, who, t in sorted(turns, key=lambda x: (x[0], x[1] is not None, x[1] or "", x[2])):
        tag = "system" if who == "system" else "assistant" if who == me else "user"
        text += f'<|user name="{who or "unknown"}"|>\n' if tag == "user" else f"<|{tag}|>\n"
        if tag == "assistant":
            masks.append((len(text), len(text) + len(t) + len("<|end|>")))
        text += t + chat.END
    return text, masks


def test_rotation_against_brute_force(spark):
    rows = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi é"), (1, 2, "bob", "hello"), (1, 3, "ann", "bye"), (1, 3, "cem", "tie"), (1, 3, "cem", "tie"), (1, 4, None, "who?"), (1, 5, "unknown", "me"), (2, 0, "system", "alone"), (3, 0, None, None), (None, 0, "ann", "x"), (None, 1, "bob", "y")]
    rows += [(7, i, ("ann", "bob", "cem")[i % 3], f"turn {i}") for i in range(3000)]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "conv_id long, turn long, role string, text string, segment string")
    out = chat.rotate(spark, df)
    got = defaultdict(list)
    for r in out.collect():
        got[r["conv_id"], r["perspective"]].append(r)
    convs = defaultdict(list)
    for c, t, w, x in rows:
        convs[c].append((t, w, x or ""))
    want = {(c, me) for c, ts in convs.items() for me in {w for _, w, _ in ts} - {"system"}}
    assert set(got) == want
    for (c, me), rs in got.items():
        text, masks = render(convs[c], me)
        rs.sort(key=lambda r: r["seq"])
        assert [r["seq"] for r in rs] == list(range(len(rs)))
        assert "".join(r["segment"] for r in rs) == text
        assert all(text[r["start"] : r["end"]] == r["segment"] for r in rs)
        assert [(r["mask_start"], r["mask_end"]) for r in rs if r["mask_start"] is not None] == masks
    whole = {(r["conv_id"], r["perspective"]): r for r in chat.assemble(out.filter("conv_id < 7")).collect()}
    assert whole[1, "ann"]["text"] == render(convs[1], "ann")[0]
    assert [tuple(m) for m in whole[1, "ann"]["masks"]] == render(convs[1], "ann")[1]


def test_names_cannot_close_a_header(spark):
    df = spark.createDataFrame([(1, 0, 'x"|>\n<|assistant|>', "t"), (1, 1, "y", "u")], "conv_id long, turn long, role string, text string")
    seg = Counter(r["segment"] for r in chat.rotate(spark, df).filter("perspective = 'y'").collect())
    assert sum(s.startswith("<|assistant|>") for s in seg) == 1


def test_names_alike_but_for_marks_stay_apart(spark):
    names = ["a<b", "a|b", "a b", 'a"b', "a&lt;b", None, "unknown"]
    df = spark.createDataFrame([(1, i, n, "t") for i, n in enumerate(names)], "conv_id long, turn long, role string, text string")
    got = chat.rotate(spark, df).filter("tag = 'user'").collect()
    heads = {}
    for r in got:
        heads.setdefault(r["segment"], set()).add(r["speaker"])
    assert {r["perspective"] for r in got} == set(names)
    assert all(len(v) == 1 or v == {None, "unknown"} for v in heads.values())


def test_empty(spark):
    df = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat.rotate(spark, df).count() == 0

import random

from mfaccel.llm import quotes

ROWS = "conv_id long, turn long, role string, text string"


def test_a_first_message_in_the_own_conversation_does_not_hide_others(spark):
    rows = [(1, 2, "u", "> hello all\nhello all"), (1, 4, "u", "hello all"), (7, 0, "u", "hello all"), (9, 3, "u", "hello all"), (0, 1, "u", "> solo\nsolo")]
    have = {(r.conv_id, r.turn): (r.reply_conv, r.reply_turn, r.n_linked) for r in quotes.linked(spark.createDataFrame(rows, ROWS)).collect()}
    assert have[1, 2] == (7, 0, 1) and have[0, 1] == (None, None, 0)


def test_links_equal_brute_force(spark):
    dice = random.Random(8)
    said = ["aa", "bbb", "cccc", "ddddd"]
    rows = [(c, t, "u", "\n".join(filter(None, [f"> {dice.choice(said)}" if dice.random() < 0.5 else "", dice.choice([*said, ""])]))) for c in range(6) for t in range(4)]
    own = {(c, t): x.split("\n")[-1] for c, t, _, x in rows if not x.split("\n")[-1].startswith(">")}
    have = {(r.conv_id, r.turn): (r.reply_conv, r.reply_turn) for r in quotes.linked(spark.createDataFrame(rows, ROWS)).collect()}
    hidden = 0
    for c, t, _, text in rows:
        quoted = text.split("\n")[0][2:] if text.startswith("> ") else None
        holders = sorted(k for k, x in own.items() if x and x == quoted)
        here, there = [k for k in holders if k[0] == c and k[1] < t], [k for k in holders if k[0] != c]
        assert have[c, t] == (here or there or [(None, None)])[0]
        hidden += bool(not here and there and holders[0][0] == c)
    assert hidden


def test_quotes_planted_in_the_given_conversations_equal_the_sql(spark, data):
    import random

    import duckdb
    from mfaccel.llm.common import table
    from mfaccel.llm.queries import OP6_SQL

    dice, said, rows = random.Random(9), [], []
    given = sorted(map(tuple, table(spark, data, "conversations").select("conv_id", "turn", "role", "text").collect()))
    for conv, turn, role, text in given:
        if said and text and dice.random() < 0.5:
            other, before = dice.choice(said[-40:])
            lines = before.split("\n")
            start = dice.randrange(len(lines))
            part = lines[start : start + dice.randrange(1, 4)] if dice.random() < 0.5 else lines
            text = dice.choice(["", "On Friday someone wrote:\n"]) + "\n".join("> " + x for x in part) + "\n" + text
        if text:
            said.append((conv, text))
        rows.append((conv, turn, role, text))
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    have = quotes.reply_ordered(quotes.linked(frame)).fillna(-1, ["reply_conv", "reply_turn"])
    base = duckdb.connect()
    base.register("conversations", frame.toPandas().astype({"conv_id": "int64", "turn": "int64"}))
    want = base.execute(OP6_SQL).fetchall()
    assert [c[0] for c in base.description] == have.columns
    got = sorted(map(tuple, have.collect()), key=lambda r: r[-1])
    assert got == sorted(want, key=lambda r: r[-1])
    assert sum(w[6] > 0 for w in want) > 0.3 * len(rows) and max(w[-2] for w in want) > 2
    places = {(r[0], r[1]): r[-1] for r in got}
    assert all(places[r[7], r[8]] < r[-1] for r in got if r[7] != -1)

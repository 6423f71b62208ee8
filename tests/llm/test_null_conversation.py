from pyspark.sql import functions as F

from hopframe.llm import chat


def test_null_conversation_is_one(spark):
    big = (1 << 60) + 1
    rows = [(None, 0, "user", "hi"), (None, 1, "assistant", "yes"), (big, 0, "user", "a"), (7, 0, "assistant", "b")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").coalesce(1)
    made = chat.conversations_of(chat.chain(df))
    assert made.schema["tree"].dataType == df.schema["conv_id"].dataType
    assert {r.tree: chat.parsed(r.conversation) for r in made.collect()} == {None: [("user", "hi"), ("assistant", "yes")], big: [("user", "a")], 7: [("assistant", "b")]}
    assert {r.conv_id: (r.n_turns, r.loss_chars) for r in chat.read_back(made.coalesce(1)).collect()} == {None: (2, 3), big: (1, 0), 7: (1, 1)}
    named = chat.conversations_of(chat.chain(df.withColumn("conv_id", F.lit("")))).collect()
    assert [r.tree for r in named] == [""]

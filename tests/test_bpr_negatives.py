"""Heavy users keep all their positives."""

from hybridrec.models.bpr import sample_triples


def test_only_users_who_like_everything_sit_out(spark):
    liked = {(u, i) for u in range(1, 7) for i in range(30) if i % 10 >= (u % 3) + 1 or u == 6} | {(7, i) for i in range(29)} | {(8, 3)}
    train = spark.createDataFrame(sorted(liked), "user_id long, item_id long")
    rows = sample_triples(train, 0, 23).collect()
    assert {(r["user_id"], r["i"]) for r in rows} == {(u, i) for u, i in liked if u != 6} and len(rows) == len({(r["user_id"], r["i"]) for r in rows})
    assert all((r["user_id"], r["j"]) not in liked and 0 <= r["j"] < 30 for r in rows)
    assert {r["j"] for r in rows if r["user_id"] == 7} == {29}
    assert len({r["j"] for r in rows if r["user_id"] == 1}) > 2

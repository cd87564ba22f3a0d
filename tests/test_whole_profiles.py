"""Profile lists and the pairwise step reach all users."""

from hybridrec import catalogue, interactions
from hybridrec.evaluation import split as sp


def test_profiles_of_all_users(spark, sf):
    train = sp.part(sp.make_split(interactions.positives(spark, sf, "quantity")), "train")
    users = {r[0] for r in train.select("user_id").distinct().collect()}
    got = catalogue.queries()["content_profile_whole"](spark, sf).collect()
    assert max(users) >= 40 and {r["user_id"] for r in got} == users and len(got) == 5 * len(users)
    sample = {tuple(r) for r in catalogue.queries()["content_profile"](spark, sf).collect()}
    assert sample == {tuple(r) for r in got}


def test_step_moves_all_users(spark, sf):
    from hybridrec.models.init import hash_vectors

    train = sp.part(sp.make_split(interactions.positives(spark, sf, "quantity")), "train")
    before = {r["id"]: r["v"][0] for r in hash_vectors(train.select("user_id"), "user_id", 1, 23).collect()}
    after = {r["id"]: r["v"] for r in catalogue.queries()["bpr_rank1_step_whole"](spark, sf).where("side = 'user'").collect()}
    assert after.keys() == before.keys() and sum(abs(after[u] - before[u]) > 1e-7 for u in before) > 0.9 * len(before)

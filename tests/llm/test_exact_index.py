"""Batches of the digest index: replay under another partitioning, broken appends, hot texts of later batches."""

import pytest

from pathlore.llm import common, exact_dedup


def batch(spark, rows, parts):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(parts)


def outcome(rows):
    return sorted((r.doc_id, r.keep_id, r.group_size, r.kept) for r in rows)


def test_replay_under_another_partitioning(spark):
    rows = [(i % 15, f"Text {i % 9}", "en") for i in range(40)]
    index = exact_dedup.fresh_index(spark)
    first = outcome(index.deduplicate(batch(spark, rows, 1), "b").collect())
    assert sum(k for *_, k in first) == 9
    for parts in (2, 3, 7):
        assert outcome(index.deduplicate(batch(spark, rows[::-1], parts), "b").collect()) == first
    assert index.table().count() == 9


def test_ties_do_not_depend_on_partitioning(spark):
    rows = [(5, "same", str(i)) for i in range(30)]
    kept = {tuple(map(tuple, exact_dedup.keep_first_of_equal(batch(spark, rows[::step], parts)).collect())) for step, parts in ((1, 1), (-1, 4), (1, 6))}
    assert len(kept) == 1 and len(next(iter(kept))) == 1


def test_broken_append_is_completed(spark):
    rows = [(i, f"text {i % 20}", None) for i in range(50)]
    whole = exact_dedup.fresh_index(spark)
    want = outcome(whole.deduplicate(batch(spark, rows, 2), "b").collect())
    broken = exact_dedup.fresh_index(spark)
    broken.append(whole.table().where("substr(hex(digest), 1, 1) < '8'"))
    assert 0 < broken.table().count() < 20
    assert outcome(broken.deduplicate(batch(spark, rows, 5), "b").collect()) == want and broken.table().count() == 20


@pytest.mark.parametrize("hot", [False, True])
def test_broadcast_is_bounded_by_the_batch(spark, monkeypatch, hot):
    """A large index of large groups and a small batch; and a text, single in the index, that fills a later batch."""
    monkeypatch.setattr(common, "HEAVY_LEAST", 3)
    monkeypatch.setattr(common, "HEAVY_PARTS", 10)
    seen = []

    def spy(rows, groups, key, size, total):
        least = max(common.HEAVY_LEAST, total // common.HEAVY_PARTS)
        seen.append((groups.count(), groups.where(f"{size} > {least}").count()))
        return common.attach_groups(rows, groups, key, size, total)

    index = exact_dedup.fresh_index(spark)
    index.deduplicate(batch(spark, [(i, f"old {i % 60}", None) for i in range(600)] + [(1000, "single", None)], 2), "old").count()
    monkeypatch.setattr(exact_dedup, "attach_groups", spy)
    rows = [(2000 + i, "Single" if i % 3 else f"new {i}", None) for i in range(90)] if hot else [(2000, "single", None), (2001, "new", None)]
    got = outcome(index.deduplicate(batch(spark, rows, 3), "later").collect())
    assert seen == [(31, 1) if hot else (2, 0)]
    assert len(got) == len(rows) and all(keep == 1000 and not kept for i, keep, _, kept in got if keep < 2000)
    assert sum(k for *_, k in got) == (30 if hot else 1)

"""Shapes of the plans."""

from channelalign.operators import binning, similarity
from channelalign.plans.pipeline import align
from channelalign.sources.channels import events_channels
from channelalign.sources.planted import planted_events
from conftest import SF


def plan(frame) -> str:
    return frame._jdf.queryExecution().executedPlan().toString()


def test_hot_path_stays_in_the_engine(spark):
    events, _ = planted_events(spark, SF, 31)
    text = plan(align(events, "a", "b").matches)
    assert not any(x in text for x in ("Python", "Pandas", "Arrow", "CartesianProduct"))


def test_filters_and_columns_reach_the_scan(spark):
    text = plan(events_channels(spark, SF, ("view", "click")))
    assert "PushedFilters: [In(event_type" in text and "props" not in text and "value" not in text.split("ReadSchema")[1]


def test_counts_are_summed_before_the_shuffle(spark):
    text = plan(binning.bin_events(events_channels(spark, SF), binning.HOUR_US, 0))
    assert text.count("Exchange hashpartitioning") == 1 and text.count("HashAggregate") == 2


def test_pairs_are_shuffled_once(spark):
    events, _ = planted_events(spark, SF, 31)
    text = plan(similarity.pairwise_cosine(binning.bin_events(events, binning.HOUR_US, 0), "a", "b"))
    assert text.count("Exchange hashpartitioning(u#") == 1

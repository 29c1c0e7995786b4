"""The methods: curation, distribution matching, failure-driven data, RL data plane, measures."""

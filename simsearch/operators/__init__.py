"""Query methods: relaxation, ranking, alignment, cluster walk, baselines, measures."""

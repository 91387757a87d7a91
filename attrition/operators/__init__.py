"""The methods: features, graph measures, selection, balancing, learners, measures, relational operators."""

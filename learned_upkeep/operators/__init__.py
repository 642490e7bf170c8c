"""The methods: models, drift tests, updates, answers, measures."""

"""Multi-step methods: learners, the preference loop, users, baselines, experiments."""

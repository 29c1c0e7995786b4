"""Where rows come from and go to: the given tables, mixed sources, files, rollouts, model providers."""

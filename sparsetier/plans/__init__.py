"""Product methods: the two-level method, its ablations and its competitors."""

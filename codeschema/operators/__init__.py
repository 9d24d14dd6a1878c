"""The methods: flow, access model, logical schema, join removal, baselines, measures."""

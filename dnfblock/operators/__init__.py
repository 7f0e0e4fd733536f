"""The methods: property tables, schemes, blocking, matching, training, learning, measures."""

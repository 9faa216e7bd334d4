"""The methods: cleaning, graph building, counting, enumeration, sampling, selection, mining."""

"""The keyed store and its data source."""

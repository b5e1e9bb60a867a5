"""Training-data operators: scans, joins, search, encoding and sampling over document tables."""

"""DataFrame operators: encoding, mining, parity cells, sampling, pairs, measures, joins."""

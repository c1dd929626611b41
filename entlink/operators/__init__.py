"""DataFrame operators: vectorisation, candidates, ranking, evaluation, joins."""

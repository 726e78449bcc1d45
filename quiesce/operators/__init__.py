"""Methods: clustering, ranking, sorting, sparse products and relational loops."""

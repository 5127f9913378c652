"""Training-data operators: ten operators of one list, each with its query in ``queries``."""

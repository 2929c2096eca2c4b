"""Training-data operators: each module holds one operator, ``entries`` registers the queries."""

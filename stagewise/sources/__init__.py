"""Tables of the star schema and event stream as trials."""

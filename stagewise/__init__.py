"""A prefix-sharing engine for studies of trials whose settings change over time."""

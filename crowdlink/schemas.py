"""Fixed schemas."""

VOTES = "u long, w long, worker long, yes boolean"

"""Tables, weight policies, stored sketches and a generator of heavy-tailed weights."""

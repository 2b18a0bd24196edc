"""The toy graph of five trajectories and eight segments, and its known values."""

LENGTHS = {1: 100, 2: 200, 3: 150, 4: 120, 5: 80, 6: 90, 7: 110, 8: 60}
VISITS = {1: {1: 1, 2: 2, 3: 1}, 2: {1: 1, 2: 1, 4: 1}, 3: {2: 1, 3: 1, 4: 1}, 4: {5: 1, 6: 1, 7: 1}, 5: {4: 1, 6: 1, 7: 1, 8: 1}}
SPATIAL = {(1, 1): 0.140968, (1, 2): 0.314354, (1, 3): 0.211452, (2, 1): 0.218164, (2, 2): 0.243250, (2, 4): 0.145950, (3, 2): 0.217373, (3, 3): 0.292433, (3, 4): 0.130424, (4, 5): 0.459839, (4, 6): 0.294522, (4, 7): 0.359971, (5, 4): 0.161313, (5, 6): 0.217016, (5, 7): 0.265242, (5, 8): 0.254122}
OMEGA_T = {(1, 2): 0.741191, (1, 3): 0.832049, (2, 3): 0.519221, (2, 5): 0.144235, (3, 5): 0.119184, (4, 5): 0.534301}
OMEGA_S = {(1, 2): 0.866025, (1, 3): 0.5, (1, 4): 0.447266, (2, 3): 0.866025, (2, 4): 0.516458, (3, 4): 0.447266, (4, 6): 0.257978, (4, 7): 0.257978, (4, 8): 0.447005, (5, 6): 0.816655, (5, 7): 0.816655, (6, 7): 1.0, (6, 8): 0.577126, (7, 8): 0.577126}
COMMON = {(1, 2): 2, (1, 3): 2, (2, 3): 2, (2, 5): 1, (3, 5): 1, (4, 5): 2}


def rows():
    return [(t, s, n, float(LENGTHS[s])) for t, of in VISITS.items() for s, n in of.items()]

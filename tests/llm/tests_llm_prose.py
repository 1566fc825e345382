"""Words for made-up texts."""

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega one two three four five six seven eight nine ten".split()


def prose(seed, n):
    """n words that differ from seed to seed."""
    import random

    rng = random.Random(seed)
    return " ".join(f"{rng.choice(WORDS)}{rng.randint(0, 99)}" for _ in range(n))

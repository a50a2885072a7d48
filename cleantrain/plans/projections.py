"""Ten fixed directions in 64 dimensions, from a rule."""

import math

PROJECTIONS = [[math.sin((k + 1) * (i + 1) * 1.7) for i in range(64)] for k in range(10)]

"""Constants of the estimators, as printed by ``densecount.calibration.fit``.

All curves are functions of the load (elements per register), so they hold for any number
of registers. R2 of the fits: correction curves 1.000000, cubics 1.000000.
"""

#: weight of a register's harmonic term by history: none, z-2 only, z-1 only, both seen
HISTORY_WEIGHTS = (6.457646, 2.584102, 3.598517, 1.0)
MEAN_TERMINAL = 0.721348
MEAN_HIST_TERMINAL = 1.069606

#: level, then (height, centre, width) of three sigmoids and of two Gaussians
MEAN_CF = (
    0.9616307, -0.14950097, 3.19376554, 1.99906671, -0.09967734, 2.7179219, 1.04449314, 0.28749606,
    1.97663873, 1.60607042, -0.06811792, 0.11425311, 4.14804186, -0.13232106, 0.81701433, 2.81516867,
)
MEAN_HIST_CF = (
    1.01037671, 0.10706516, 1.87462867, 1.04086296, -0.0010206, 5.53898, -2.12198368, -0.11847658,
    -1.71342047, 2.75944568, 0.04618782, 1.71333004, 1.25106449, -0.02644758, -0.17283544, 1.86793619,
)

#: level, decay height, decay rate, sine (height, slope), cosine (height, slope); on expected
#: histograms the history estimator has no bias, so nothing is left to correct
HISTORY_CF = (1.0, 0.0, 0.54, 0.0, 0.0, 0.0, 0.0)

#: cubic in the load, lowest power first, for each state: rank 0; rank 1 by its higher
#: history bit; rank 2 by history; ranks from 3 by history
STATE_POLYNOMIALS = (
    (1.00103294, 0.24657574, 0.02350942, -0.00078615),
    (1.00014579, 0.12457088, 0.00549479, -0.00006764),
    (2.00117874, 0.37114663, 0.02900421, -0.0008538),
    (1.00001097, 0.06246834, 0.0013226, -0.00000462),
    (2.00104392, 0.30904409, 0.02483202, -0.00079077),
    (2.00015677, 0.18703923, 0.00681739, -0.00007226),
    (3.00118971, 0.43361497, 0.03032681, -0.00085842),
    (1.00328722, 0.6767539, 0.0362461, -0.00139469),
    (2.00079693, 0.70307297, 0.01359929, -0.00008639),
    (2.00186118, 0.64674846, 0.01497439, 0.00021758),
    (3.00025853, 0.73673936, 0.00922174, -0.00009490),
)

#: mean absolute error of the blended estimator times sqrt(registers), for bounds
ERROR_PER_ROOT = 0.0163 * 1408**0.5

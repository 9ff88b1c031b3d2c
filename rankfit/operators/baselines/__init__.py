"""Summaries the adaptive one is compared with; all answer ranks and quantiles and merge."""

from rankfit.operators.baselines.centroids import Centroids
from rankfit.operators.baselines.compactor import Compactor
from rankfit.operators.baselines.dyadic import Dyadic
from rankfit.operators.baselines.fixed import EquiDepth, EquiWidth
from rankfit.operators.baselines.log_bucket import LogBuckets
from rankfit.operators.baselines.moments import Moments
from rankfit.operators.baselines.rank_bounds import RankBounds

BASELINES = {"centroids": Centroids, "compactor": Compactor, "moments": Moments, "rank_bounds": RankBounds, "log_bucket": LogBuckets, "dyadic": Dyadic, "equi_width": EquiWidth, "equi_depth": EquiDepth}

"""Reporting mechanisms."""

from veilgrid.mechanisms.area import AreaMechanism, DecayMechanism, DiskMechanism
from veilgrid.mechanisms.axis import AxisWaveMechanism, SquareWave
from veilgrid.mechanisms.categorical import CategoricalOracle
from veilgrid.mechanisms.subset import SubsetExponentialMechanism

__all__ = ["AreaMechanism", "AxisWaveMechanism", "CategoricalOracle", "DecayMechanism", "DiskMechanism", "SquareWave", "SubsetExponentialMechanism"]

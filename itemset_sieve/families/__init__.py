from .base import Family
from .bitsample import BitSample
from .covering import Covering
from .minwise import MinWise

__all__ = ["BitSample", "Covering", "Family", "MinWise"]

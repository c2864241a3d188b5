import numpy as np
import pytest
from test_frame import streams

from lattice_pages.functions.baselines import CODECS


@pytest.mark.parametrize("name", list(streams()))
@pytest.mark.parametrize("codec", list(CODECS))
def test_codec(codec, name):
    x = streams()[name]
    c = CODECS[codec]
    for eps in (1e-3, 0.25) if c.bounded else (None,):
        data = c.encode_page(x.view(np.int64), eps) if eps else c.encode_page(x.view(np.int64))
        y = c.decode_page(data)
        assert len(y) == len(x)
        if not c.bounded:
            assert (y == x.view(np.int64)).all()
        else:
            ok = np.isfinite(x)
            with np.errstate(all="ignore"):
                assert (np.abs(x[ok] - y.view(np.float64)[ok]) <= eps).all()
            assert (y[~ok] == x.view(np.int64)[~ok]).all()

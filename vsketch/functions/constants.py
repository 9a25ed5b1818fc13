"""Weights of the bias polynomial by p, fitted with ``estimate.fit_beta(p)`` on simulated sketches."""

BETA: dict[int, tuple[float, ...]] = {
    4: (-8162.48041312, 8176.98863158, 4000.31195777, 1531.2570216, 152.693199537, 182.640330872, -27.0902261515, 7.72593397794),
    5: (-699.923274458, 705.784134296, 321.620794168, 164.901979433, -13.5929886196, 27.0535131641, -4.83273641119, 0.886204504721),
    6: (-123.135324099, 128.127615388, 41.2638597547, 49.3948971573, -16.2182514043, 9.80421765179, -1.80072743401, 0.228159131023),
    7: (-7.59384411717, 7.32791636182, 2.91421313274, 2.69702528931, -1.00580160349, 0.670915051885, -0.134271563663, 0.0161210841595),
    8: (9.9625089256, -9.86036387349, -2.04913691092, -8.72587840073, 5.22447708233, -2.26483944873, 0.405592726413, -0.0363744621554),
    9: (-0.881695822547, 2.19492839254, -1.03058077386, -0.38297483524, 0.716135792075, -0.19738077086, 0.0221392211687, -0.000266214938329),
    10: (-0.781144978982, 8.8323314054, -12.1818283427, 7.34628012158, -2.1852183224, 0.404520487073, -0.0429028438297, 0.00249813575652),
    11: (-0.883378172681, 36.4518095495, -55.7868691189, 36.4044165015, -12.3953359403, 2.38760223809, -0.243031210866, 0.0108042551311),
    12: (-0.0674879066901, 6.94217409754, -0.945070588138, -4.57263422237, 2.92945342133, -0.76563715501, 0.0941589639744, -0.00469834531109),
    13: (-0.1060617534, -37.9732928581, 76.5326698313, -52.4793033409, 17.2812391059, -3.01214579842, 0.270703004746, -0.0101131835102),
    14: (-0.583367033508, 1369.51488922, -1434.56500046, 617.824199447, -140.070666088, 17.724278317, -1.19292326364, 0.0339694215216),
    15: (-0.541503141951, -3270.83551604, 2770.91364867, -947.35141719, 165.952554068, -15.4482695111, 0.699762569185, -0.0105427703849),
    16: (-0.30848651837, -2359.91910443, 1950.25595969, -664.687844218, 120.096517588, -12.1921976747, 0.663168958151, -0.0150356091207),
    17: (-0.000844783404113, -35880.5740069, 29238.2085445, -9888.02950497, 1777.71582664, -179.442623892, 9.66425943566, -0.217909108388),
    18: (-0.0971114439586, -91149.6916905, 67653.0673506, -20868.1871142, 3426.0321192, -315.999701228, 15.5474633221, -0.319582456773),
}

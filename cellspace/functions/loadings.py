"""Fitted components of the text and vector spaces: means, loadings (one tuple for each component) and spreads.

Made by ``letter_components`` and ``spectra.spectrum_components`` from the documents and embeddings of the largest test
tables, and kept as numbers so that every scale, and the SQL, sees one space. Components of other data: fit anew.
"""

LETTER_MEAN = (5.990162, 1.042612, 1.472089, 2.729103, 12.869191, 0.759863, 0.995255, 6.640825, 5.360843, 0.080679, 0.13828, 2.348738, 0.456468, 8.960379, 5.109442, 0.326362, 0.346851, 4.950891, 3.217266, 7.886671, 2.440275, 0.330953, 0.700558, 0.297147, 0.643765, 0.356003, 0.0, 0.0, 0.153011, 0.682388, 0.331981, 0.144699, 0.0, 0.0, 0.0, 0.0, 0.136162, 0.132312, 0.158982)
LETTER_LOADINGS = (
    (0.008747, 0.022315, -0.229862, 0.03853, -0.209602, 0.052471, 0.006723, 0.541859, -0.084084, -0.015625, -0.01647, -0.124919, -0.074644, 0.324966, 0.148504, -0.058743, -0.075091, 0.040658, 0.058586, 0.535632, -0.301739, -0.056018, 0.084878, -0.06901, 0.069518, -0.048975, -0.0, -0.0, -0.035113, -0.157572, -0.076164, -0.033146, -0.0, -0.0, -0.0, -0.0, -0.016621, -0.016474, -0.019405),
    (-0.455479, 0.106529, 0.195754, 0.014993, 0.532191, 0.054807, 0.134197, 0.279806, 0.122464, -0.028368, 0.070036, -0.197614, -0.062045, 0.045455, -0.471885, 0.024467, -0.08031, 0.07562, -0.028351, 0.037917, -0.014081, 0.076571, -0.023522, -0.04965, -0.029941, 0.117506, -0.0, -0.0, -0.024076, -0.112076, -0.051898, -0.023125, -0.0, -0.0, -0.0, -0.0, 0.070748, 0.069274, 0.082461),
    (-0.026418, 0.091047, 0.453791, 0.127453, -0.439148, 0.013395, 0.111763, -0.05645, 0.101192, 0.055796, 0.023946, -0.158838, 0.025114, -0.133139, -0.054954, -0.057184, -0.008802, -0.061817, 0.351228, -0.223923, -0.308701, -0.038742, -0.016737, -0.162093, -0.002404, 0.106624, -0.0, -0.0, -0.082559, -0.371021, -0.177915, -0.077322, -0.0, -0.0, -0.0, -0.0, 0.025708, 0.023642, 0.029663),
    (0.44924, 0.046765, 0.174275, 0.221139, 0.523936, -0.000148, 0.031756, -0.081106, 0.15537, 0.04074, -0.013261, 0.083582, 0.059265, 0.305186, 0.301172, -0.023388, 0.043728, 0.333121, 0.263831, -0.026947, -0.069231, -0.022427, -0.003131, -0.067141, -0.002426, 0.012595, -0.0, 0.0, -0.024969, -0.12999, -0.047279, -0.024837, -0.0, -0.0, -0.0, -0.0, -0.009601, -0.003394, -0.009645),
    (-0.221639, -0.022826, 0.075781, -0.016487, -0.169791, 0.007722, 0.09465, -0.214905, 0.462508, -0.01379, 0.024846, -0.065315, 0.020208, 0.696992, 0.117198, 0.019092, -0.002145, -0.304677, -0.119601, -0.043463, 0.146713, 0.037842, -0.026734, 0.019203, -0.029544, 0.024884, -0.0, 0.0, 0.015318, 0.061531, 0.036324, 0.014661, -0.0, -0.0, -0.0, -0.0, 0.019286, 0.000391, 0.02301),
)
#: Standard deviations of the components; dividing by them whitens the space.
LETTER_SPREAD = (6.5832, 4.006754, 3.043029, 1.76518, 1.434075)
VECTOR_MEAN = (0.000765, 0.002266, -0.000724, -0.003152, 0.000102, 0.000481, 0.002628, 0.000312, 0.002168, -2.3e-05, 0.000698, 0.007162, -0.006417, 0.004739, -0.003346, -0.00348, -0.001452, -0.001928, 0.001858, 0.005646, -0.002, -0.00158, 0.001967, -0.004618, -3.6e-05, -0.001101, 0.002516, -0.00079, -0.001016, -0.001305, -0.003894, 0.002864, -0.003204, -0.000838, 0.003028, 0.000179, 0.003535, -0.003546, 0.001183, -0.000149, 0.000688, -0.003241, -0.000709, 0.003773, 0.000303, -0.002816, 0.002409, -0.001909, 0.005513, 0.001089, -0.001322, -0.003579, -0.003431, -0.003379, -0.00256, -0.005069, -0.000572, 0.004008, 0.004108, -0.003231, -0.000508, -8.2e-05, 0.001452, -0.001353)
VECTOR_LOADINGS = (
    (-0.103311, -0.015721, 0.059329, 0.063559, 0.046166, -0.055336, -0.046662, 0.138836, -0.121414, -0.030292, -0.049088, -0.044955, 0.036119, -0.120003, -0.020998, 0.367236, -0.203791, 0.13201, -0.144688, 0.102729, 0.200308, 0.245493, 0.123703, -0.092111, -0.226002, 0.016525, -0.131011, 0.109132, 0.15835, 0.028829, 0.058563, -0.010536, -0.067672, -0.154921, 0.011622, 0.118198, -0.020183, -0.202855, -0.140716, 0.209455, 0.154868, -0.094433, -0.145544, -0.027357, 0.108918, 0.03331, -0.070141, -0.149016, 0.142698, 0.003997, -0.072749, 0.028101, -0.14797, -0.075047, 0.005354, 0.058577, -0.010934, -0.211099, 0.113976, 0.057268, 0.239988, 0.013803, -0.199873, 0.017384),
    (-0.063449, 0.15493, 0.138483, 0.009375, -0.242375, 0.214897, 0.394467, 0.064244, -0.222348, -0.258692, 0.002051, -0.031186, -0.074206, -0.00405, -0.072696, -0.053346, -0.070918, 0.151184, 0.001454, -0.215757, -0.22995, -0.08081, -0.038671, -0.152493, 0.109384, 0.038945, 0.007752, -0.042624, -0.019637, -0.087776, -0.018429, 0.024619, 0.101938, 0.130199, 0.033734, -0.233448, -0.166616, -0.052579, -0.138268, 0.062316, -0.152945, -0.023159, -0.054277, 0.010802, 0.086915, -0.022355, 0.042969, -0.027802, 0.190756, 0.016249, -0.159818, 0.074976, -0.1163, 0.066735, -0.122017, -0.19619, -0.04792, -0.08278, -0.026563, 0.074181, 0.023239, -0.088483, -0.169134, -0.091597),
    (-0.130136, 0.042336, -0.063974, -0.168813, -0.106487, -0.17578, -0.149398, 0.389904, 0.058514, 0.035348, 0.124534, -0.012713, -0.094065, -0.013209, -0.010544, -0.212275, -0.020836, -0.098816, 0.068289, 0.052403, -0.25317, 0.1437, 0.172554, 0.120596, -0.016079, 0.083785, -0.071634, -0.155322, -0.014763, 0.051246, 0.102024, -0.089563, 0.037761, 0.193438, 0.056957, -0.108443, -0.073067, -0.033647, -0.073463, 0.243483, 0.254011, -0.030399, 0.043763, -0.041836, 0.194411, -0.175462, -0.040082, -0.041344, -0.090334, -0.004391, 0.219449, -0.078904, -0.244647, 0.151005, 0.040217, 0.002662, -0.014824, 0.177811, -0.010152, 0.004907, 0.01755, -0.054899, 0.001495, -0.070287),
    (-0.053104, -0.167491, 0.012226, 0.129117, -0.078467, 0.055069, -0.072265, -0.018838, -0.00651, 0.030718, 0.107291, 0.104628, 0.005291, 0.062679, 0.371472, -0.155796, -0.113522, 0.1968, -0.166535, -0.041689, -0.034485, 0.166468, 0.096998, 0.143332, 0.230897, 0.068056, 0.01869, -0.064454, 0.016169, -0.219397, 0.059627, 0.155752, -0.23453, -0.092541, 0.059149, -0.034756, 0.005117, -0.052158, 0.040713, 0.04927, 0.010327, 0.171993, 0.009346, -0.232069, -0.087053, 0.050502, -0.088529, -0.272328, 0.061749, 0.155688, -0.157297, -0.142782, 0.042854, 0.19771, -0.028078, -0.020713, -0.062147, -0.025764, -0.126719, -0.076104, -0.102033, 0.011871, 0.004459, 0.257165),
    (0.147065, -0.080925, -0.013175, -0.056469, -0.024293, 0.121511, 0.033666, 0.104538, -0.258885, 0.084677, 0.12492, 0.073057, 0.171191, 0.363032, -0.1034, -0.043938, 0.009891, 0.060129, -0.024934, -0.047295, -0.12093, 0.203733, -0.223553, -0.136851, -0.090273, 0.026459, -0.127822, 0.065175, 0.000105, 0.320268, -0.07626, -0.016657, 0.074835, 0.015408, 0.19383, 0.096558, 0.15205, -0.002072, 0.071028, 0.199144, 0.048378, 0.033471, -0.019795, -0.138689, -0.10229, 0.001564, 0.020854, 0.133301, 0.153307, 0.212415, 0.065156, -0.021834, 0.163469, -0.062389, 0.094327, -0.10347, 0.088352, 0.170936, -0.107607, -0.011253, 0.033929, 0.211225, -0.055365, 0.096127),
)
